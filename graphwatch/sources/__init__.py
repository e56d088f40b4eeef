"""Edge and vertex tables from files and from the given tables."""
