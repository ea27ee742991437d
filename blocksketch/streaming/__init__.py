"""Sketches and gates over Structured Streaming."""
