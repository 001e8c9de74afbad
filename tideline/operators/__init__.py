"""operators of the ordered graph engine."""
