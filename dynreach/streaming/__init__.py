"""Structured Streaming over update operations."""
