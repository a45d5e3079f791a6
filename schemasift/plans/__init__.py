"""The stages of schema filtering, their training, baselines, measures and workloads."""
