"""Structured Streaming over reward events."""
