"""streaming of normgraph."""
