"""Edge partitioning of very large graphs as Spark DataFrame plans."""
