"""Descent rounds over a stream."""
