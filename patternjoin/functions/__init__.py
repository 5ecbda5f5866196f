"""functions of the pattern-join engine."""
