"""Operators of the curation method, its baselines and its measures."""
