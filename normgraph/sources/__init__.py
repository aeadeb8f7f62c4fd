"""sources of normgraph."""
