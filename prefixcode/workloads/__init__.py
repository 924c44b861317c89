"""The experiments on the given tables, and all queries with their SQL."""
