"""Structured Streaming over graphs."""
