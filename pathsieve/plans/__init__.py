"""Index construction, query answering, baselines and measures."""
