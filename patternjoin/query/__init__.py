"""query of the pattern-join engine."""
