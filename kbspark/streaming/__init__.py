"""Structured Streaming forms of the knowledge-base loop."""
