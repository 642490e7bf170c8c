"""Insertions as a stream."""
