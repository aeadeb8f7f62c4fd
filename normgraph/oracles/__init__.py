"""oracles of normgraph."""
