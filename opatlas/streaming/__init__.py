"""Incremental twins of the batch methods on Structured Streaming."""
