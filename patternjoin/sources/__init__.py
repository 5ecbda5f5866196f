"""sources of the pattern-join engine."""
