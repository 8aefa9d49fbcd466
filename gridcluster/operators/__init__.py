"""Operators of grid clustering, its baselines and measures."""
