"""Table access and release storage."""
