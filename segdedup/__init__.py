"""Release-wise fuzzy deduplication with immutable band-key segments, on Spark."""
