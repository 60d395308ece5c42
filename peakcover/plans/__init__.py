"""Workloads and staging."""
