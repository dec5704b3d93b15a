"""Iterative analytics."""
