"""plans of normgraph."""
