"""Structured Streaming: arriving records, requests and replies."""
