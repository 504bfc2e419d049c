"""Methods over the graph."""
