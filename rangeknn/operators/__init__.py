"""Ranking, graphs, indexes, searches, baselines and measures."""
