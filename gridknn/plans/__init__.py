"""Whole methods, measures, workloads and the query registry."""
