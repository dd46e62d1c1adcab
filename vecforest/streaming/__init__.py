"""Structured Streaming: encoding, insertion, queries, windows, drift."""
