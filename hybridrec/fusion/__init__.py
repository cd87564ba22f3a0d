"""Combining several content features."""
