"""Workloads of the study on the given tables, and the registry of queries."""
