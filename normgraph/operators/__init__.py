"""operators of normgraph."""
