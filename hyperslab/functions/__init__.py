"""Encodings, SQL functions and measures."""
