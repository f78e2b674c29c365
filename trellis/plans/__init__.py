"""Queries, statistics, costs and join orders."""
