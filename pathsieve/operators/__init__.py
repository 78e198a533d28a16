"""Executors, baselines and operators on their results."""
