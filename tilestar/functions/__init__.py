"""functions of tilestar."""
