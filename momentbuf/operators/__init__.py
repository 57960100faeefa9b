"""Buffers, their queries and updates, baselines and applications."""
