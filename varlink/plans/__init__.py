"""Query plans over the given tables: the repository of virtual tables, the registry of queries, and the workloads."""
