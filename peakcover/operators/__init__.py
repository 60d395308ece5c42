"""Placement methods and their baselines."""
