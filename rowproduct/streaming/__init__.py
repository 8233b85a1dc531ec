"""Products over streams."""
