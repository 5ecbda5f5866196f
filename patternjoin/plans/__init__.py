"""plans of the pattern-join engine."""
