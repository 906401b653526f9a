"""A live inverted index for Spark: postings, codes, block chains, queries and their cost measures."""
