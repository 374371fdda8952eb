"""Incremental counterparts on Structured Streaming."""
