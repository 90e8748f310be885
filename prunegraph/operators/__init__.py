"""Operators of the graph-inference engine."""
