"""plans of the distinct-counting engine."""
