"""Polygon layers, text and binary forms, index storage."""
