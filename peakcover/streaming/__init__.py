"""Placement over streams."""
