"""Operators of walks on evolving graphs, for Spark."""
