"""Streams around the engine: edges, counts, sessions, requests."""
