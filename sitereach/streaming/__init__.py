"""Structured Streaming over check-ins."""
