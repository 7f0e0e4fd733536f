"""Registered queries by topic; each module adds to the one catalogue."""
