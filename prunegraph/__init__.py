"""prunegraph: cheap graph-network inference as Spark DataFrame plans."""
