"""Belief propagation on large discrete factor graphs, written for Spark."""
