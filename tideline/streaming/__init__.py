"""streaming of the ordered graph engine."""
