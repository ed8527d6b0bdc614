"""Main and weight models."""
