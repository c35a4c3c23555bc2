"""Streams of edges: windows, maintained degrees, and answers by delta."""
