"""Structured Streaming forms of the serving methods."""
