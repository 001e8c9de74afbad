"""plans of the ordered graph engine."""
