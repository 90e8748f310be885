"""Streaming of the graph-inference engine."""
