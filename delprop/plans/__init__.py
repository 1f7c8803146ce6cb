"""Cost model, choice of method, workloads, and the registered queries with their SQL."""
