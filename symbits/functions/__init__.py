"""Symmetric functions, and what SQL users can call."""
