"""Evaluation of patterns, and the relational operators around it."""
