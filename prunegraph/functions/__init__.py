"""Functions of the graph-inference engine."""
