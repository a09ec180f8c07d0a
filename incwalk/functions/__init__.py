"""Column functions: coins and closed forms."""
