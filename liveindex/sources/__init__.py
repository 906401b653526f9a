"""Collections, query logs, line files, and the data source of stored indexes."""
