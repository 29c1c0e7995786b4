"""Structured Streaming twins of the methods."""
