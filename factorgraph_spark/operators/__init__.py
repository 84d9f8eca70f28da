"""Inference, partitioning, baselines and measures on factor graphs."""
