"""The experiments' queries on the given tables."""
