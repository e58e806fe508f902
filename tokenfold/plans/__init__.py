"""Workloads and the queries that run them."""
