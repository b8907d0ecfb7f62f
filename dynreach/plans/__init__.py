"""Planners that put operators together: batches of updates, workloads, the relational surface."""
