"""Structured Streaming: new points, windows and drift."""
