"""Graphs built from tables, and readers and writers of graphs, patterns and groups."""
