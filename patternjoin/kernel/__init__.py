"""kernel of the pattern-join engine."""
