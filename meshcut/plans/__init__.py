"""Registered queries, workloads and the cost model."""
