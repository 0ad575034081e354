"""Structured Streaming forms of the monitor and the feed."""
