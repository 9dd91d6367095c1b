"""Table readers and the workloads' vector sets."""
