"""Column expressions on path rows: primitives, restrictors, conditions, projection terms."""
