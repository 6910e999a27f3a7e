"""Matrices of event streams."""
