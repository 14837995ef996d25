"""Part of the semiring graph engine."""
