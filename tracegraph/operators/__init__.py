"""Trace operators: layouts, pruning, the four queries, replicas, baselines."""
