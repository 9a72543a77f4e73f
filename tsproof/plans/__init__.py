"""Logical plans: streams over the given tables, positions, workloads and the choice of a path."""
