"""functions of the distinct-counting engine."""
