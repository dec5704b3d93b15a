"""Joins and edge builders that Spark lacks."""
