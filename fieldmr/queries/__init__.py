"""Queries by family; each module fills one registry."""
