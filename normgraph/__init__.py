"""normgraph: rules in text to machine-checkable constraints, and constraints over large tables, on Spark."""
