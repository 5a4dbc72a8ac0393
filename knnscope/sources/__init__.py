"""Point views, readers and writers."""
