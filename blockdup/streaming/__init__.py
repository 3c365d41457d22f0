"""Structured Streaming versions of windows, state and lookup."""
