"""operators of the pattern-join engine."""
