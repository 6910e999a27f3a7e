"""Matrices as relations on Spark: relational and linear-algebra operators in one lazy query."""
