"""Activity tables from files, the canonical ones of the workloads, and a catalog."""
