"""operators of the distinct-counting engine."""
