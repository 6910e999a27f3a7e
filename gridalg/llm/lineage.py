"""Lineage cuts, as in the rest of the library."""

from gridalg.functions.lineage import cut

__all__ = ["cut"]
