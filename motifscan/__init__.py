"""motifscan: finds every instance of a small sample graph in a very large data graph, on Spark."""
