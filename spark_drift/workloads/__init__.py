"""The experiments, re-expressed on the given tables or on generated streams."""
