"""Structured Streaming: annotations of windowed results (an extension of our own)."""
