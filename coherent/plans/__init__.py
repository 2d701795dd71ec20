"""Workloads on the given tables, the SQL surface, and the query catalogue with its SQL."""
