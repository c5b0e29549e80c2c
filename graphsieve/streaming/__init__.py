"""Structured Streaming forms over files of events."""
