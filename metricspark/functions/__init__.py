"""Metrics, pruning bounds and the SQL surface."""
