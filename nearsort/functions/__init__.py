"""Column functions: blocking keys and matchers."""
