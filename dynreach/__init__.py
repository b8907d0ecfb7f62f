"""Reachability queries on graphs that keep changing, for Spark."""
