"""Product operators and the applications built on them."""
