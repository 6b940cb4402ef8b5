"""Readers of points, and writers."""
