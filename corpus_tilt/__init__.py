"""Targeted training-data selection on Spark: a small weight model learns which generic examples help a specific set."""
