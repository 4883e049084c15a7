"""Workloads, timed runs and comparisons."""
