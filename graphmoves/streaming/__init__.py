"""Edges from event streams."""
