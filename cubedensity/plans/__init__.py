"""Measures, method choice, workloads and the query registry."""
