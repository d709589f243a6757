"""Workload generators: shapes, logs of patterns, windows, two-time rewrites."""
