"""Auxiliary operators that decide where rows go: hash, range and sample partitioning, rebalance, merge."""
