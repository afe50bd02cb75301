"""Relational plans around the vector operators."""
