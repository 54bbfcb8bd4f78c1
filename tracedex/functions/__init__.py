"""Column functions: symbol strings, times, buckets."""
