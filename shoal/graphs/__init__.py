"""Graphs built from relational tables."""
