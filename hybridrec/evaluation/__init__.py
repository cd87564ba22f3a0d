"""Protocol and measures."""
