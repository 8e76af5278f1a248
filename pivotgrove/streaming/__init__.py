"""Structured Streaming: insertion, windows, state."""
