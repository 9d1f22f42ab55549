"""Relational operators around the clustering, as queries."""
