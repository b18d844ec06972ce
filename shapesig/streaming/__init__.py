"""Streams of shapes: windowed rings, probes of a stored index, incremental index."""
