"""Choice of path, workloads and evaluation."""
