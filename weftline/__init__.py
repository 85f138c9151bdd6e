"""Weftline: batches of similar machine-learning pipelines as one Spark plan."""
