"""sources of tilestar."""
