"""Graphs and the tables they are derived from."""
