"""Whole methods, workloads, and relational queries."""
