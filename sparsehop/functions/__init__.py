"""Semirings, vectors and column helpers."""
