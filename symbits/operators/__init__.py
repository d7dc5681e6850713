"""Bitmap index, bitmap algebra, circuits and the counting methods."""
