"""streaming of tilestar."""
