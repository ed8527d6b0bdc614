"""Readers, writers, tasks and splits."""
