"""Search over pipelines: policies, halving, incremental feedback."""
