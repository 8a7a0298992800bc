"""Structured Streaming over the disclosure feed."""
