"""Structured Streaming: windows, deduplication and online learning."""
