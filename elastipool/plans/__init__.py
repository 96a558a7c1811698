"""Whole runs: configurations, policies, workloads, and the query catalogue."""
