"""Graphs made from tables, and graph files."""
