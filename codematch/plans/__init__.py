"""Workload plans and the registry of queries."""
