"""operators of tilestar."""
