"""Column functions, deterministic randomness and SQL text."""
