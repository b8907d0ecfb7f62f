"""Index construction, queries, updates, baselines, generators and measures."""
