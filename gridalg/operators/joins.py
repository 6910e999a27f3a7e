"""Joins of two matrices on dimensions, values or both, with a merge function."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from gridalg.catalog import Scheme
from gridalg.functions.merge import Flags, MergeFn
from gridalg.operators.cells import HEAVY, Limits, TooLarge, densify, nonzeros, salted
from gridalg.plans.cost import SHAPES, order_of

STRATEGIES = ("auto", "sparse", "densify", "nested_loop", "bloom", "bloom_sparse")


@dataclass(frozen=True)
class Operand:
    cells: DataFrame
    nrows: int
    ncols: int
    #: Entries that count, at most, if known.
    size: int | None = None

    def expected(self, key: str) -> int | None:
        """Different keys of the operand, at most, if known."""
        if key == "val":
            return self.size
        n = self.nrows if key == "rid" else self.ncols
        return n if self.size is None else min(n, self.size)

    def dense(self, limits: Limits) -> DataFrame:
        return densify(self.cells, self.nrows, self.ncols, limits.grid)


def place(cells: DataFrame, scheme: Scheme, n: int | None = None) -> DataFrame:
    """The entries dealt by row or by column, marked for broadcast, or as they lie."""
    if scheme == Scheme.B:
        return F.broadcast(cells)
    if scheme == Scheme.XI:
        return cells
    key = "rid" if scheme == Scheme.R else "cid"
    return cells.repartition(n, key) if n else cells.repartition(key)


def result_dims(shape: str) -> list[tuple[str, str]]:
    """Side and attribute behind each dimension of the result: the shared dimension first, then a's, then b's."""
    pairs = SHAPES[shape]
    shared = [p for p in pairs if "val" not in p]
    a = [x for x in ("rid", "cid") if x not in [p[0] for p in shared]]
    b = [y for y in ("rid", "cid") if y not in [p[1] for p in shared]]
    return [("a", p[0]) for p in shared] + [("a", x) for x in a] + [("b", y) for y in b]


def _sides(a: Operand, b: Operand, shape: str, flags: Flags, strategy: str, limits: Limits) -> tuple[DataFrame, DataFrame]:
    """The entries that can matter: nonzeros where the other side's zeros annihilate, all cells where not."""
    if strategy in ("densify", "nested_loop") or (strategy == "bloom" and shape == "val=val"):
        if shape == "val=val" and flags.z0 and strategy != "densify":
            return a.cells.filter("val IS NOT NULL"), b.cells.filter("val IS NOT NULL")
        return a.dense(limits), b.dense(limits)
    if shape == "val=val":
        # equal values meet, so a zero meets only zeros: f(0, 0) decides for both
        return (nonzeros(a.cells), nonzeros(b.cells)) if flags.z0 else (a.dense(limits), b.dense(limits))
    return nonzeros(a.cells) if flags.sx else a.dense(limits), nonzeros(b.cells) if flags.sy else b.dense(limits)


def placed(cells: DataFrame, scheme: Scheme, key: str | None, n: int | None) -> DataFrame:
    """The entries by the scheme that a plan chose. A scheme by another dimension than the join's key would be dealt again, so it is left."""
    if scheme == Scheme.B or (key, scheme) in (("rid", Scheme.R), ("cid", Scheme.C)):
        return place(cells, scheme, n)
    return cells


def _filtered(x: DataFrame, y: DataFrame, kx: str, ky: str, expected: int | None, smaller_first: bool) -> tuple[DataFrame, DataFrame]:
    """The larger of two sides without the rows whose key a filter of the smaller side's keys rules out."""
    from gridalg.operators.bloom import bloom_semijoin

    if smaller_first:
        return x, bloom_semijoin(y, x, expected=expected, keys=(ky, kx))
    return bloom_semijoin(x, y, expected=expected, keys=(kx, ky)), y


def join_cells(a: Operand, b: Operand, shape: str, f: MergeFn, flags: Flags, *, strategy: str = "auto", limits: Limits = Limits(), schemes: tuple[Scheme, Scheme] | None = None, n: int | None = None) -> DataFrame:
    """rid, cid, val for overlays, d1.. and val for the other predicates.

    Result cells that are not listed are zero; listed ones may be zero too, but not where both inputs are and f
    keeps zero. NULLs of one-sided matches count as zeros, stored NULLs give what f makes of NULL.
    """
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy {strategy!r}: one of {', '.join(STRATEGIES)}")
    order = order_of(shape)
    if shape in ("overlay", "transpose"):
        return _overlay(a, b, shape, f, flags, strategy, limits, schemes, n)
    pairs = SHAPES[shape]
    if strategy in ("bloom", "bloom_sparse") and not pairs:
        raise ValueError("a cross product has no key to filter by")
    left, right = _sides(a, b, shape, flags, strategy, limits)
    if schemes:
        left, right = (placed(c, s, pairs[0][i] if pairs else None, n) for i, (c, s) in enumerate(zip((left, right), schemes, strict=True)))
    x = left.select(F.col("rid").alias("ar"), F.col("cid").alias("ac"), F.col("val").alias("av"))
    y = right.select(F.col("rid").alias("br"), F.col("cid").alias("bc"), F.col("val").alias("bv"))
    name = lambda side, k: F.col(side + {"rid": "r", "cid": "c", "val": "v"}[k])
    smaller_first = (a.size if a.size is not None else a.nrows * a.ncols) <= (b.size if b.size is not None else b.nrows * b.ncols)
    if not pairs:
        if a.nrows * a.ncols * b.nrows * b.ncols > limits.output and strategy != "sparse":
            rows = left.count() * right.count()
            if rows > limits.output:
                raise TooLarge(f"a cross product of {rows} entries is over the limit of {limits.output}")
        both = x.crossJoin(y)
    elif strategy == "nested_loop" and shape == "val=val":
        both = _all_values(left, right, a.size, b.size, limits)
    elif strategy == "nested_loop":
        # as a difference, so that the planner does not make an equi-join of it
        both = x.crossJoin(y).filter((name("a", pairs[0][0]) - name("b", pairs[0][1])) == 0)
    else:
        p, q = pairs[0]
        if "val" in (p, q) and p != q:  # a value equals an id: only whole values within the dimension can
            side, bound = ("a", b.nrows if q == "rid" else b.ncols) if p == "val" else ("b", a.nrows if p == "rid" else a.ncols)
            v = name(side, "val")
            whole = (v == F.floor(v)) & (v >= 0) & (v < bound)
            key = v.cast("long")
            x, y = (x.filter(whole).withColumn("k", key), y.withColumn("k", name("b", q))) if side == "a" else (x.withColumn("k", name("a", p)), y.filter(whole).withColumn("k", key))
            if strategy in ("bloom", "bloom_sparse"):  # the ids that have entries rule out values
                ids = b.expected(q) if side == "a" else a.expected(p)
                x, y = _filtered(x, y, "k", "k", ids, side == "b")
            both = x.join(y, "k")
        else:
            kx, ky = "a" + {"rid": "r", "cid": "c", "val": "v"}[p], "b" + {"rid": "r", "cid": "c", "val": "v"}[q]
            if strategy in ("bloom", "bloom_sparse"):
                x, y = _filtered(x, y, kx, ky, a.expected(p) if smaller_first else b.expected(q), smaller_first)
            both = x.join(y, F.col(kx) == F.col(ky))
    if flags.z0 and not (flags.sx or flags.sy) and shape != "val=val" and strategy != "densify":
        both = both.filter("NOT (av = 0 AND bv = 0)")
    dims = [name(s, k).alias(f"d{i + 1}") for i, (s, k) in enumerate(result_dims(shape))]
    assert len(dims) == order
    return both.select(*dims, f(F.col("av"), F.col("bv")).cast("double").alias("val"))


#: Entries with the same value that one row holds, about.
BUNCH = 1000


def _bunches(cells: DataFrame, side: str, size: int | None) -> DataFrame:
    """Entries of equal value together, so that a value is compared once for all of them; one value spreads over several rows."""
    n = max(1, -(-(size if size is not None else cells.count()) // BUNCH))
    deal = F.pmod(F.xxhash64("rid", "cid"), F.lit(n))
    return cells.groupBy(F.col("val").alias(f"{side}v"), deal.alias("z")).agg(F.collect_list(F.struct(F.col("rid").alias(f"{side}r"), F.col("cid").alias(f"{side}c"))).alias(f"{side}s")).drop("z")


def _all_values(left: DataFrame, right: DataFrame, na: int | None, nb: int | None, limits: Limits) -> DataFrame:
    """Entries of equal value by a nested loop over all pairs of bunches. As two inequalities, so that the planner does not make an equi-join of it."""
    x, y = _bunches(left, "a", na), _bunches(right, "b", nb)
    if na is not None and na <= limits.broadcast and (nb is None or na <= nb):
        x = F.broadcast(x)
    elif nb is not None and nb <= limits.broadcast:
        y = F.broadcast(y)
    pairs = x.crossJoin(y).filter("av >= bv AND av <= bv")
    return pairs.select("av", "bv", "bs", F.inline("as")).select("av", "bv", "ar", "ac", F.inline("bs"))


def _overlay(a, b, shape, f, flags, strategy, limits, schemes, n) -> DataFrame:
    other = b.cells
    if shape == "transpose":
        other = other.select(F.col("cid").alias("rid"), F.col("rid").alias("cid"), "val")
        b = Operand(other, b.ncols, b.nrows)
    m, k = max(a.nrows, b.nrows), max(a.ncols, b.ncols)
    if strategy in ("densify", "nested_loop") or not (flags.sx or flags.sy or flags.z0):
        x, y, how = densify(a.cells, m, k, limits.grid), densify(other, m, k, limits.grid), "inner"
    elif flags.sx and flags.sy:
        x, y, how = nonzeros(a.cells), nonzeros(other), "inner"
    elif flags.sx:
        x, y, how = nonzeros(a.cells), other, "left"
    elif flags.sy:
        x, y, how = a.cells, nonzeros(other), "right"
    else:
        x, y, how = a.cells, other, "full"
    if strategy in ("bloom", "bloom_sparse"):
        raise ValueError("an overlay meets on two ids, it has no key to filter by")
    if schemes and how in ("inner", "left", "right"):  # an outer side cannot be sent everywhere
        x = placed(x, schemes[0], None, n) if how != "left" else x
        y = placed(y, schemes[1], None, n) if how != "right" else y
    x = x.select("rid", "cid", F.col("val").alias("av"), F.lit(True).alias("ia"))
    y = y.select("rid", "cid", F.col("val").alias("bv"), F.lit(True).alias("ib"))
    both = x.join(y, ["rid", "cid"], how)
    av = F.when(F.col("ia"), F.col("av")).otherwise(0.0)
    bv = F.when(F.col("ib"), F.col("bv")).otherwise(0.0)
    return both.select("rid", "cid", f(av, bv).cast("double").alias("val"))


def output_size(a: Operand, b: Operand, shape: str) -> int:
    """Rows of a one-dimension join on nonzeros: sum over the shared id of products of counts, from two small aggregates."""
    (p, q), *_ = SHAPES[shape]
    x = nonzeros(a.cells).groupBy(F.col(p).alias("k")).agg(F.count("*").alias("x"))
    y = nonzeros(b.cells).groupBy(F.col(q).alias("k")).agg(F.count("*").alias("y"))
    return x.join(y, "k").agg(F.sum(F.col("x").cast("decimal(38,0)") * F.col("y"))).first()[0] or 0


def fused_totals(a: Operand, b: Operand, shape: str) -> DataFrame:
    """One row: number and sum of the rows of a one-dimension join with f = x * y, from counts and sums of each shared id."""
    (p, q), *_ = SHAPES[shape]
    x = nonzeros(a.cells).groupBy(F.col(p).alias("k")).agg(F.count("*").alias("nx"), F.sum("val").alias("x"))
    y = nonzeros(b.cells).groupBy(F.col(q).alias("k")).agg(F.count("*").alias("ny"), F.sum("val").alias("y"))
    return x.join(y, "k").agg(F.coalesce(F.sum(F.col("nx") * F.col("ny")), F.lit(0)).alias("n"), F.sum(F.col("x") * F.col("y")).alias("total"))


def fused_sum(a: Operand, b: Operand, shape: str, over: str) -> DataFrame:
    """The sum over one dimension of a one-dimension join with f = x * y, without the join's rows.

    Over the shared dimension it is a matrix product (d2, d3, val); over a free one, that side is summed first.
    """
    (p, q), *_ = SHAPES[shape]
    fa, fb = ("cid" if p == "rid" else "rid"), ("cid" if q == "rid" else "rid")
    x = nonzeros(a.cells).select(F.col(p).alias("k"), F.col(fa).alias("d2"), F.col("val").alias("x"))
    y = nonzeros(b.cells).select(F.col(q).alias("k"), F.col(fb).alias("d3"), F.col("val").alias("y"))
    if over == "d1":
        return x.join(y, "k").groupBy("d2", "d3").agg(F.sum(F.col("x") * F.col("y")).alias("val"))
    if over == "d2":
        x = x.groupBy("k").agg(F.sum("x").alias("x"))
        return x.join(y, "k").select(F.col("k").alias("d1"), "d3", (F.col("x") * F.col("y")).alias("val"))
    y = y.groupBy("k").agg(F.sum("y").alias("y"))
    return x.join(y, "k").select(F.col("k").alias("d1"), "d2", (F.col("x") * F.col("y")).alias("val"))


def join_salted(a: Operand, b: Operand, shape: str, f: MergeFn, heavy: int = HEAVY) -> DataFrame:
    """A one-dimension join on nonzeros (f must annihilate on both sides) with heavy shared ids of a split over tasks."""
    (p, q), *_ = SHAPES[shape]
    fa, fb = ("cid" if p == "rid" else "rid"), ("cid" if q == "rid" else "rid")
    x = nonzeros(a.cells).select(F.col(p).alias("k"), F.col(fa).alias("d2"), F.col("val").alias("av"))
    y = nonzeros(b.cells).select(F.col(q).alias("k"), F.col(fb).alias("d3"), F.col("val").alias("bv"))
    return salted(x, y, "d2", heavy).select(F.col("k").alias("d1"), "d2", "d3", f(F.col("av"), F.col("bv")).cast("double").alias("val"))
