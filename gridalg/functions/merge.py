"""Merge functions of joins, and the probe that finds where they annihilate at zero."""

from __future__ import annotations

import math
import random
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, SparkSession, functions as F


@dataclass(frozen=True)
class Flags:
    """sx: f(0, y) = 0 for all y; sy: f(x, 0) = 0 for all x; z0: f(0, 0) = 0."""

    sx: bool
    sy: bool
    z0: bool


def _zero(x) -> bool:
    return x is not None and not math.isnan(x) and x == 0


@dataclass(frozen=True)
class MergeFn:
    """A function of two values as a Column expression. declare overrides the probe, for functions it cannot judge."""

    fn: Callable[[Column, Column], Column]
    name: str = "f"
    declare: Flags | None = None

    def __call__(self, x: Column, y: Column) -> Column:
        return self.fn(x, y)

    def flags(self, spark: SparkSession, seed: int = 17) -> Flags:
        """Evaluates f at zero against two different nonzero samples on either side.

        For f linear in each argument two points fix the restriction to a zero argument, so the answer is exact;
        NULL, NaN and infinite results do not annihilate. The rows are literals: no job reads data.
        """
        if self.declare is not None:
            return self.declare
        rng = random.Random(seed)
        s1 = rng.uniform(1, 2)
        s2 = s1 + rng.uniform(1, 2)
        points = [(0.0, s1), (0.0, s2), (s1, 0.0), (s2, 0.0), (0.0, 0.0)]
        row = spark.range(1).select(*[self.fn(F.lit(x), F.lit(y)).cast("double").alias(f"p{i}") for i, (x, y) in enumerate(points)]).first()
        p = [_zero(row[i]) for i in range(5)]
        return Flags(p[0] and p[1] and p[4], p[2] and p[3] and p[4], p[4])


MUL = MergeFn(lambda x, y: x * y, "mul")
ADD = MergeFn(lambda x, y: x + y, "add")
LEFTY = MergeFn(lambda x, y: x * (y + 1), "lefty")
MAX = MergeFn(lambda x, y: F.greatest(x, y), "max")
ADD1 = MergeFn(lambda x, y: x + y + 1, "add1")
