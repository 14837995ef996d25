"""Graph algorithms over the semiring operations."""
