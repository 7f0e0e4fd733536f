"""Whole pipelines and experiments."""
