"""Structured Streaming in front of the engine."""
