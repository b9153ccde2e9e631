"""Graphs from tables and files, node numbering, and physical layouts."""
