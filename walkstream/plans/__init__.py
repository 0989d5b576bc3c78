"""Stored state and iteration."""
