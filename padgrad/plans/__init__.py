"""Cost-based choices, workloads and the catalogue of queries."""
