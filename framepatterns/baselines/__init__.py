"""Baselines: serial library, stock engine, broadcast-only joins, brute force."""
