"""Operators for large training-data pipelines; self-contained and optional."""
