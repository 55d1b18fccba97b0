"""Column functions and token rules."""
