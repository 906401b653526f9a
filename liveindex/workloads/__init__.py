"""The experiment workloads, as queries with oracles."""
