"""Watching the workload and moving what it needs."""
