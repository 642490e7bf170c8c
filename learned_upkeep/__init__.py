"""Keeps learned table models accurate while rows are inserted: detect drift, then keep, fine-tune or distil."""
