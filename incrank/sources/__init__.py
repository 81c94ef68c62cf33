"""Edge lists, batches of changes, and the workloads made from the given tables."""
