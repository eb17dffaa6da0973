"""sources of the distinct-counting engine."""
