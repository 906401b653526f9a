"""Index operators: postings, growth rules, packing, search, collation and conversion."""
