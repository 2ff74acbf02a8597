"""Explanation narratives on Spark: attribution, writing, grading, validation, guarding."""
