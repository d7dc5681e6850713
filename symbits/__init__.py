"""Symmetric Boolean queries over bitmap indexes, as Spark plans."""
