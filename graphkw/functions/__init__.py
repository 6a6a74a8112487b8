"""Column functions and query generation."""
