"""Live ingest, operation streams and windows."""
