"""Structured Streaming around the mined graphs."""
