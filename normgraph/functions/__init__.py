"""functions of normgraph."""
