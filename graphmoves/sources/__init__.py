"""Graphs of the given tables, generators and file formats."""
