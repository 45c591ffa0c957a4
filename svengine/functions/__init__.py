"""Column functions and gate algebra."""
