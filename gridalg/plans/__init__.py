"""Logical plans over matrices: nodes, rewrites, costs and placement."""
