"""Walks, derived graphs, matchings, trees, and their measures."""
