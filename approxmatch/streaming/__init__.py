"""Streams against a static index, windows and deduplication."""
