"""Partitioned input and output."""
