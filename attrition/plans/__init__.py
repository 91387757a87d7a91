"""Whole workloads: named queries with the SQL they must equal, and the experiments."""
