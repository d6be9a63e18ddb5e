"""Pattern-targeted plans, workloads and the query registry."""
