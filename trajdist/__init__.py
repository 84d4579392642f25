"""Exact proximity search over moving-object trajectories, for Spark."""
