"""Content features of items."""
