"""streaming of the pattern-join engine."""
