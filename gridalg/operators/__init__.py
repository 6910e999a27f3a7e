"""Lowering of plans to DataFrames of entries, tiles and tensors."""
