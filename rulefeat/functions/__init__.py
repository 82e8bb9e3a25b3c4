"""Measures as columns and SQL functions."""
