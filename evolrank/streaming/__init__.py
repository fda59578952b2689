"""Feeds of edges with Structured Streaming."""
