"""Choosing an access path."""
