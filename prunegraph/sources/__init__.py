"""Sources of the graph-inference engine."""
