"""Output-sensitive regular path queries on Spark DataFrames."""
