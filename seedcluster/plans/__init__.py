"""Whole methods, experiments and the query registry."""
