"""Column helpers for operators that stay in DataFrame functions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, functions as F


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value) with the value computed once, however often it is used."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def fold(size: Column, state: Column, step: Callable[[Column, Column], Column], kind: str) -> Column:
    """What a run over 0 .. size-1 appends, as array<kind>: step(s, i) gives struct(s, o), the next state and an array to append.

    A plain aggregate copies its growing array in each step, which is quadratic. Here blocks of about the cube root
    of the size collect their own arrays, and the blocks are flattened once: some size ** 4/3 copies.
    """
    none = F.expr(f"cast(array() as array<{kind}>)")
    nones = F.expr(f"cast(array() as array<array<{kind}>>)")

    def run(block: Column) -> Column:
        def inner(acc: Column, i: Column) -> Column:
            return let(step(acc["s"], i), lambda y: F.struct(y["s"].alias("s"), F.concat(acc["o"], y["o"]).alias("o")))

        def outer(acc: Column, k: Column) -> Column:
            part = F.sequence(k * block, F.least(size, (k + 1) * block) - 1)
            done = F.aggregate(part, F.struct(acc["s"].alias("s"), none.alias("o")), inner)
            return let(done, lambda y: F.struct(y["s"].alias("s"), F.concat(acc["o"], F.array(y["o"])).alias("o")))

        blocks = F.sequence(F.lit(0), F.floor((size - 1) / block).cast("int"))
        return F.flatten(F.aggregate(blocks, F.struct(state.alias("s"), nones.alias("o")), outer)["o"])

    return F.when(size > 0, let(F.greatest(F.lit(32), F.ceil(F.cbrt(size)).cast("int")), run)).otherwise(none)


def fresh(columns: list[str], *names: str) -> list[str]:
    """The names, with underscores before those that a table has already."""
    taken = {c.lower() for c in columns}
    out = []
    for n in names:
        while n.lower() in taken:
            n = "_" + n
        taken.add(n.lower())
        out.append(n)
    return out
