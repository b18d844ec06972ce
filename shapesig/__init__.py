"""Approximate polygon similarity search on Spark: shape signatures, bucket lookup, exact refinement."""
