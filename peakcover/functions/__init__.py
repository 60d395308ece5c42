"""Shared geometry and measures."""
