"""Structured Streaming around the index: query streams, upserts, windows, result caches with a life time."""
