"""Plans over matrices as DataFrames of entries (rid, cid, val): all JVM-side, in codegen."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from gridalg.catalog import NULL, ZERO
from gridalg.functions.predicate import And, Theta, all_of
from gridalg.plans.nodes import Agg, Elem, Inverse, Map, Masked, MatMul, Node, NonEmpty, Ones, Scalar, Select, Source, Transpose


class TooLarge(RuntimeError):
    """A dense form or a join result beyond the limit of the engine."""


@dataclass(frozen=True)
class Limits:
    #: Cells that a dense grid may have, and rows that a join may give.
    grid: int = 50_000_000
    output: int = 1_000_000_000
    #: Side of a matrix that one task inverts.
    inverse: int = 2048
    #: Entries of an operand that may be broadcast.
    broadcast: int = 1_000_000
    #: Entries of an operand that a Bloom filter is made of without being asked for.
    bloom: int = 8_000_000


NONZERO = "val IS NOT NULL AND val <> 0"


def nonzeros(cells: DataFrame) -> DataFrame:
    return cells.filter(NONZERO)


def grid(spark: SparkSession, m: int, n: int, limit: int) -> DataFrame:
    """All (rid, cid): the side that is longer spreads over tasks, the other is repeated by a generator."""
    if m * n > limit:
        raise TooLarge(f"a grid of {m} x {n} cells is over the limit of {limit}")
    if m >= n:
        return spark.range(m).select(F.col("id").alias("rid"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))).alias("cid"))
    return spark.range(n).select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(m - 1).cast("long"))).alias("rid"), F.col("id").alias("cid"))


def densify(cells: DataFrame, m: int, n: int, limit: int) -> DataFrame:
    """Every cell, zeros included; stored NULLs stay NULL."""
    stored = cells.withColumn("__s", F.lit(True))
    return grid(cells.sparkSession, m, n, limit).join(stored, ["rid", "cid"], "left").select("rid", "cid", F.when(F.col("__s"), F.col("val")).otherwise(0.0).alias("val"))


def region(n: Node) -> Theta | None:
    """The dims-only selection that holds for all cells of a plan, if any."""
    if isinstance(n, Select):
        inner = region(n.a)
        own = all_of([c for c in n.theta.conjuncts() if c.dims_only()])
        return own if inner is None else inner if own is None else And(inner, own)
    if isinstance(n, Transpose):
        inner = region(n.a)
        return None if inner is None else inner.swapped()
    if isinstance(n, (Scalar, Map, Masked)):
        return region(n.a)
    if isinstance(n, Elem):
        return all_of([x for x in (region(n.a), region(n.b)) if x is not None])
    if isinstance(n, (MatMul, Agg)):
        a, b = region(n.a), region(n.b) if isinstance(n, MatMul) else None
        keep_rows = isinstance(n, MatMul) or n.dim == "r"
        rows = [c for c in a.conjuncts() if c.uses() <= {"rid"}] if a is not None and keep_rows else []
        other = b if isinstance(n, MatMul) else a if n.dim == "c" else None
        cols = [c for c in other.conjuncts() if c.uses() <= {"cid"}] if other is not None else []
        return all_of(rows + cols)
    return None


def aggregate(cells: DataFrame, fn: str, dim: str, shape: tuple[int, int], absent: str) -> DataFrame:
    """One partial and one final hash aggregation; lines without stored cells are left out."""
    m, n = shape
    rid, cid = {"r": ("rid", None), "c": (None, "cid"), "d": (None, None), "a": (None, None)}[dim]
    if dim == "d":
        cells = cells.filter("rid = cid")
    length = {"r": n, "c": m, "d": m, "a": m * n}[dim]
    nnz = F.count_if(F.col("val").isNotNull() & (F.col("val") != 0)).cast("double")
    stored = F.count("*")
    if fn == "sum":
        value = F.sum("val")
        value = F.coalesce(value, F.lit(0.0))
    elif fn == "nnz":
        value = nnz
    elif fn == "avg":
        value = F.try_divide(F.sum("val"), nnz)
    else:
        best = F.max("val") if fn == "max" else F.min("val")
        pick = F.greatest if fn == "max" else F.least
        value = F.when(stored < length, pick(F.coalesce(best, F.lit(0.0)), F.lit(0.0))).otherwise(best) if absent == ZERO else best
    keys = [k for k in (rid, cid) if k]
    out = cells.groupBy(*keys).agg(value.alias("val")) if keys else cells.agg(value.alias("val"))
    zero = F.lit(0).cast("long")
    return out.select((F.col("rid") if rid else zero).alias("rid"), (F.col("cid") if cid else zero).alias("cid"), "val")


PRODUCTS = ("auto", "broadcast_a", "broadcast_b", "shuffle_inner", "row_stationary", "salted")
#: Entries of one shared id on the left side beyond which it is split.
HEAVY = 100_000


def salted(x: DataFrame, y: DataFrame, spread: str, heavy: int) -> DataFrame:
    """x and y joined on k, with ids of more than `heavy` entries in x split by a hash of the column `spread`.

    Each part of x meets its own copy of y's entries of that id, so no task holds all of x's. The split ids are at most
    the entries of x over `heavy`, and only they are broadcast.
    """
    split = x.groupBy("k").agg(F.count("*").alias("c")).filter(F.col("c") > heavy).select("k", F.ceil(F.col("c") / heavy).cast("int").alias("s"))
    split = F.broadcast(split)
    left = x.join(split, "k", "left").withColumn("z", F.when(F.col("s").isNotNull(), F.pmod(F.hash(spread), F.col("s"))).otherwise(0)).drop("s")
    right = y.join(split, "k", "left").withColumn("z", F.explode(F.when(F.col("s").isNotNull(), F.sequence(F.lit(0), F.col("s") - 1)).otherwise(F.array(F.lit(0))))).drop("s")
    return left.join(right, ["k", "z"])


def multiply(a: DataFrame, b: DataFrame, small: str | None = None, strategy: str = "auto", heavy: int = HEAVY) -> DataFrame:
    """Sum over the shared id of products of entries; NULLs count for nothing. small: the side to broadcast.

    shuffle_inner deals both sides by the shared id; row_stationary keeps the rows of a where they are, sends b
    everywhere and deals the result by row, so that a row-placed a needs no exchange at all; salted splits inner ids of
    more than `heavy` entries.
    """
    if strategy not in PRODUCTS:
        raise ValueError(f"strategy {strategy!r}: one of {', '.join(PRODUCTS)}")
    small = {"broadcast_a": "a", "broadcast_b": "b", "row_stationary": "b"}.get(strategy, small)
    x = a.filter("val IS NOT NULL").select(F.col("rid"), F.col("cid").alias("k"), F.col("val").alias("x"))
    y = b.filter("val IS NOT NULL").select(F.col("rid").alias("k"), F.col("cid"), F.col("val").alias("y"))
    if strategy == "salted":
        return salted(x, y, "rid", heavy).groupBy("rid", "cid").agg(F.sum(F.col("x") * F.col("y")).alias("val"))
    if small == "a":
        x = F.broadcast(x)
    elif small == "b":
        y = F.broadcast(y)
    elif strategy == "shuffle_inner":
        x, y = x.repartition("k").hint("merge"), y.repartition("k")
    return x.join(y, "k").groupBy("rid", "cid").agg(F.sum(F.col("x") * F.col("y")).alias("val"))


def add(a: DataFrame, b: DataFrame, null_absent: bool) -> DataFrame:
    """a + b; NULL plus anything is NULL."""
    if null_absent:
        return a.withColumnRenamed("val", "x").join(b.withColumnRenamed("val", "y"), ["rid", "cid"]).select("rid", "cid", (F.col("x") + F.col("y")).alias("val"))
    both = a.unionByName(b)
    return both.groupBy("rid", "cid").agg(F.when(F.count("*") > F.count("val"), None).otherwise(F.sum("val")).alias("val"))


def times(a: DataFrame, b: DataFrame, absent: tuple[str, str]) -> DataFrame:
    x, y = a.withColumnRenamed("val", "x"), b.withColumnRenamed("val", "y")
    how = {(ZERO, NULL): "right", (NULL, ZERO): "left"}.get(absent, "inner")
    value = F.coalesce("x", F.lit(0.0)) * F.col("y") if how == "right" else F.col("x") * F.coalesce("y", F.lit(0.0)) if how == "left" else F.col("x") * F.col("y")
    return x.join(y, ["rid", "cid"], how).select("rid", "cid", value.alias("val"))


def divide(a: DataFrame, b: DataFrame) -> DataFrame:
    """At the entries of a; a divisor that is zero, absent or NULL gives NULL, except that zero over anything is zero."""
    x, y = a.withColumnRenamed("val", "x"), b.withColumnRenamed("val", "y")
    return x.join(y, ["rid", "cid"], "left").select("rid", "cid", F.when(F.col("x") == 0, 0.0).otherwise(F.try_divide("x", "y")).alias("val"))


def factor_rows(cells: DataFrame, by: str) -> DataFrame:
    """A thin matrix as one array a row (by rid) or a column (by cid): id, vec, entries in order of the other id.

    All entries must be stored; k of them fit an array.
    """
    other = "cid" if by == "rid" else "rid"
    pairs = F.array_sort(F.collect_list(F.struct(F.col(other).alias("k"), F.col("val").alias("v"))))
    return cells.groupBy(F.col(by).alias("id")).agg(F.transform(pairs, lambda p: p["v"]).alias("vec"))


def dot(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: a * b), F.lit(0.0), lambda acc, v: acc + v)


def masked_product(a: DataFrame, w: DataFrame, h: DataFrame) -> DataFrame:
    """rid, cid, val of a and s = (w x h) there, for rows w(id, vec) and columns h(id, vec)."""
    at = nonzeros(a)
    return at.join(w.select(F.col("id").alias("rid"), F.col("vec").alias("wv")), "rid").join(h.select(F.col("id").alias("cid"), F.col("vec").alias("hv")), "cid").select("rid", "cid", "val", dot(F.col("wv"), F.col("hv")).alias("s"), "wv", "hv")


def invert(cells: DataFrame, d: int, limit: int) -> DataFrame:
    """The inverse, in one task of d * d cells at most limit * limit."""
    if d > limit:
        raise TooLarge(f"an inverse of side {d} is over the limit of {limit}")

    def run(pdf):
        import numpy as np
        import pandas as pd

        x = np.zeros((d, d))
        x[pdf["rid"], pdf["cid"]] = pdf["val"].fillna(0.0)
        y = np.linalg.inv(x)
        r, c = np.indices((d, d))
        return pd.DataFrame({"rid": r.ravel(), "cid": c.ravel(), "val": y.ravel()})

    return cells.withColumn("__g", F.lit(0)).groupBy("__g").applyInPandas(run, "rid long, cid long, val double")


def lower(n: Node, spark: SparkSession, limits: Limits) -> DataFrame:
    """The entries of a plan. Nothing runs, except that sources may already be checkpoints."""
    go = lambda x: lower(x, spark, limits)
    if isinstance(n, Source):
        return n.cells
    if isinstance(n, Ones):
        return grid(spark, n.m, n.n, limits.grid).withColumn("val", F.lit(1.0))
    if isinstance(n, Transpose):
        return go(n.a).select(F.col("cid").alias("rid"), F.col("rid").alias("cid"), "val")
    if isinstance(n, Scalar):
        a = go(n.a)
        if n.op == "*":
            return a.withColumn("val", F.col("val") * n.beta)
        if n.a.absent == ZERO:
            a = densify(a, *n.shape, limits.grid)
            inside = region(n.a)
            if inside is not None:
                a = a.filter(inside.column())
        return a.withColumn("val", F.col("val") + n.beta)
    if isinstance(n, Elem):
        a, b = go(n.a), go(n.b)
        if n.op == "+":
            return add(a, b, n.absent == NULL)
        return times(a, b, (n.a.absent, n.b.absent)) if n.op == "*" else divide(a, b)
    if isinstance(n, MatMul):
        small = None
        for side, x in (("b", n.b), ("a", n.a)):
            if isinstance(x, Source) and x.meta.bound() <= limits.broadcast:
                small = side
        return multiply(go(n.a), go(n.b), small)
    if isinstance(n, Map):
        a = go(n.a)
        if not n.keeps and n.a.absent == ZERO:
            a = densify(a, *n.shape, limits.grid)
        return a.withColumn("val", n.fn(F.col("val")))
    if isinstance(n, Masked):
        s = masked_product(go(n.a), factor_rows(go(n.w), "rid"), factor_rows(go(n.h), "cid"))
        x = F.log("s") if n.g == "log" else F.col("s")
        return s.select("rid", "cid", (F.col("val") * x if n.op == "*" else F.try_divide(F.col("val"), x)).alias("val"))
    if isinstance(n, Inverse):
        return invert(go(n.a), n.shape[0], limits.inverse)
    if isinstance(n, Select):
        a = go(n.a)
        if n.theta.dims_only():
            return a.filter(n.theta.column())
        zero = n.theta.at_zero()
        if n.a.absent == NULL or zero is False:
            return a.filter(n.theta.column())
        dims = all_of([c for c in n.theta.conjuncts() if c.dims_only()])
        values = all_of([c for c in n.theta.conjuncts() if not c.dims_only()])
        if values.at_zero() is None or (dims is not None and values.at_zero() is False):
            if values.at_zero() is None:  # absent zeros meet it in some cells only
                a = densify(a, *n.shape, limits.grid)
            return a.filter(n.theta.column())
        a = a if dims is None else a.filter(dims.column())
        return a.withColumn("val", F.when(values.column(), F.col("val")))
    if isinstance(n, NonEmpty):
        a = go(n.a)
        key = "rid" if n.dim == "r" else "cid"
        if n.treat_absent_as == ZERO and n.a.absent == ZERO:
            return a  # a line of zeros is not empty, only one of NULLs is, and that is stored in full
        some = a.filter("val IS NOT NULL").select(key).distinct()
        return a.join(some, key, "left_semi").select("rid", "cid", "val")
    if isinstance(n, Agg):
        return aggregate(go(n.a), n.fn, n.dim, n.a.shape, n.a.absent)
    raise TypeError(type(n).__name__)
