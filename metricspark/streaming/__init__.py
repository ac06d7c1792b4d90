"""Streaming inserts, standing queries and windows."""
