"""Column functions and aggregate templates."""
