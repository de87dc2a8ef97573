"""Base relations: readers and token policies."""
