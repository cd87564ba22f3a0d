"""Interactions and new items as streams."""
