"""Ranked tree-pattern search on labelled graphs, on Spark."""
