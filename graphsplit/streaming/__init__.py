"""Graphs that grow: interaction weights from event streams, and placement of new nodes."""
