"""Views over the given tables, readers and writers."""
