"""Streaming construction of graphs."""
