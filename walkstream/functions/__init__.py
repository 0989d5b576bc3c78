"""Keyed random numbers, parameters and registered functions."""
