"""Structured Streaming uses of splitters."""
