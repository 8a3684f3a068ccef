"""Structured Streaming over traffic observations."""
