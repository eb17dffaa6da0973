"""streaming of the distinct-counting engine."""
