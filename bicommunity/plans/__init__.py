"""Snapshot and continuous queries, baselines, measures and workloads."""
