"""Predicates, merge functions and column helpers."""
