"""functions of the ordered graph engine."""
