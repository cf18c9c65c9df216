"""Whole counting plans, ablations, workloads and the query registry."""
