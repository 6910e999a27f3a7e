"""Order of products in a chain, by dynamic programming over dimensions and densities."""

from __future__ import annotations

from gridalg.plans.nodes import MatMul, Node, Select, product_density
from gridalg.functions.predicate import equals_on


def chain_of(n: Node) -> list[Node]:
    """Factors of nested products, left to right."""
    return chain_of(n.a) + chain_of(n.b) if isinstance(n, MatMul) else [n]


def _rows(n: Node) -> int:
    return 1 if isinstance(n, Select) and equals_on(n.theta, "rid") is not None else n.shape[0]


def _cols(n: Node) -> int:
    return 1 if isinstance(n, Select) and equals_on(n.theta, "cid") is not None else n.shape[1]


def best_order(parts: list[Node]) -> Node:
    """The cheapest tree; ties keep the leftmost split."""
    k = len(parts)
    rows, cols = [_rows(p) for p in parts], [_cols(p) for p in parts]
    inner = [p.shape[1] for p in parts]
    best: dict[tuple[int, int], tuple[float, float, Node]] = {(i, i): (0.0, parts[i].density, parts[i]) for i in range(k)}
    for span in range(1, k):
        for i in range(k - span):
            j = i + span
            found = None
            for s in range(i, j):
                (ca, da, a), (cb, db, b) = best[i, s], best[s + 1, j]
                cost = ca + cb + rows[i] * inner[s] * cols[j] * da * db
                if found is None or cost < found[0] * (1 - 1e-12):
                    found = (cost, product_density(da, db, inner[s]), (a, b))
            best[i, j] = (found[0], found[1], MatMul(*found[2]))
    return best[0, k - 1][2]
