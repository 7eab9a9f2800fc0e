"""Plan helpers: lineage cuts, checked broadcasts."""
