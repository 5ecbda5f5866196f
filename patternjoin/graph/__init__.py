"""graph of the pattern-join engine."""
