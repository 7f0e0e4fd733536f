"""Learned schemes on streams."""
