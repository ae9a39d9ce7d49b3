"""Appending to an index from a stream, and windowed measures."""
