"""Whole pipelines, workloads and the registered queries."""
