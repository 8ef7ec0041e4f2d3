"""Edge streams and incremental traversal."""
