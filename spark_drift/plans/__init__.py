"""Planning helpers: lineage cuts and the choice of a physical distance method."""
