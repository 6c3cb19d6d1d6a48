"""Edges from event streams, and communities kept up to date."""
