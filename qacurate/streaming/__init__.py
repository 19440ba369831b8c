"""Structured Streaming: windows, state, incremental deduplication and leak checks."""
