"""Centring, hashing, bucket lookup, exact refinement, search and measures."""
