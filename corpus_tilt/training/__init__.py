"""The two-level loop, the other strategies, measures and experiments."""
