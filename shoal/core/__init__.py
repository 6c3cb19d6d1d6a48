"""Graphs as DataFrames, partitions, and the loop runtime."""
