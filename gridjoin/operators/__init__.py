"""Baselines and relational operators."""
