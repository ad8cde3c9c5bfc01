"""Structured Streaming forms of the methods."""
