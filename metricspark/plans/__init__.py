"""Cost model, measures and workloads."""
