"""plans of tilestar."""
