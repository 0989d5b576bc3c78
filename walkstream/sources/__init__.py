"""Graphs, edge lists and update logs."""
