"""Workloads and the query catalogue."""
