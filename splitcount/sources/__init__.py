"""Stored sketch tables and generated input."""
