"""Registered queries, their SQL, and the experiments."""
