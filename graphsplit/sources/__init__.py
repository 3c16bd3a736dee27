"""Graphs from tables, generated graphs, and graph files."""
