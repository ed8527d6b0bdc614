"""Sampling filters, gradients, measures and relational operators."""
