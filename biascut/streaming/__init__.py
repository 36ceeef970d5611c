"""Sketches and windowed statistics of edge streams with Structured Streaming."""
