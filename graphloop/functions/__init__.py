"""Scalar functions of query expressions."""
