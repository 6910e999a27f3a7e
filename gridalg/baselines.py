"""Stand-ins for the ways of working that the methods are compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from gridalg.api import Engine, Matrix
from gridalg.functions.lineage import cut
from gridalg.functions.merge import MergeFn
from gridalg.operators.cells import aggregate, multiply

#: Rule sets of the ablations.
SELECT_RULES = frozenset({"R1", "R2", "R3", "R4", "R5", "R6c", "R17", "R29"})
AGGREGATE_RULES = frozenset({"R7", "R9", "R11", "R12", "R13", "R16", "R19", "R20", "R21", "R23", "R25", "R29", "R30", "R39"})
CHAIN_RULES = frozenset({"R31"})
PROFILES = {
    "all": Engine(),
    "noopt": Engine(rules=frozenset(), strategy="densify"),
    "pushdown": Engine(rules=SELECT_RULES | AGGREGATE_RULES),
    "order": Engine(rules=CHAIN_RULES),
    "none": Engine(rules=frozenset()),
}


def product_first(x: Matrix, fn: str, dim: str) -> DataFrame:
    """Aggregates a product that was built and written in full, as a store without pushdown does."""
    g = cut(multiply(x.T.cells(), x.cells()))
    return aggregate(g, fn, dim, (x.shape[1], x.shape[1]), "zero")


def dense_blocks(x: Matrix, fn: str, dim: str, side: int = 100) -> float:
    """The same by the block matrices of Spark's own linear algebra library, whose products are dense."""
    from pyspark.mllib.linalg.distributed import CoordinateMatrix, MatrixEntry

    entries = x.cells().rdd.map(lambda r: MatrixEntry(r[0], r[1], r[2]))
    b = CoordinateMatrix(entries, *x.shape).toBlockMatrix(side, side)
    g = b.transpose().multiply(b).toCoordinateMatrix().entries
    if dim == "d":
        return g.filter(lambda e: e.i == e.j).map(lambda e: e.value).sum()
    return g.map(lambda e: e.value).sum()


def rdd_rowsum(x: Matrix) -> DataFrame:
    """Row sums of the Gram matrix by the pushed-down plan, over tuples instead of columns."""
    cells = x.cells().rdd.map(lambda r: (r[0], (r[1], r[2])))
    sums = cells.mapValues(lambda e: e[1]).reduceByKey(lambda p, q: p + q)
    out = cells.join(sums).map(lambda kv: (kv[1][0][0], kv[1][0][1] * kv[1][1])).reduceByKey(lambda p, q: p + q)
    return out.map(lambda kv: (kv[0], 0, float(kv[1]))).toDF("rid long, cid long, val double")


def cross_then_filter(a: Matrix, b: Matrix, on: tuple[str, str], f: MergeFn) -> DataFrame:
    """A join on one dimension as all pairs that are filtered afterwards."""
    x = a.cells().select(F.col("rid").alias("ar"), F.col("cid").alias("ac"), F.col("val").alias("av"))
    y = b.cells().select(F.col("rid").alias("br"), F.col("cid").alias("bc"), F.col("val").alias("bv"))
    p, q = f"a{on[0][0]}", f"b{on[1][0]}"
    fa, fb = ("ac" if p == "ar" else "ar"), ("bc" if q == "br" else "br")
    # the comparison of differences keeps the pairs from becoming an equi-join
    both = x.crossJoin(y).filter(F.abs(F.col(p) - F.col(q)) < 1)
    return both.select(F.col(p).alias("d1"), F.col(fa).alias("d2"), F.col(fb).alias("d3"), f(F.col("av"), F.col("bv")).alias("val"))


def hashed(m: Matrix) -> Matrix:
    """The matrix with its entries dealt by a hash of both ids, the placement of an engine without a cost model."""
    return Matrix.of(m.cells().repartition("rid", "cid"), *m.shape, engine=Engine(placement=False))


def chunked(m: Matrix, side: int = 1000) -> DataFrame:
    """rblk, cblk, rid, cid, val dealt by chunk and written, as an array store loads a matrix."""
    block = lambda c: F.floor(F.col(c) / side)
    n = int(m.spark.conf.get("spark.sql.shuffle.partitions"))
    return cut(m.cells().select(block("rid").alias("rblk"), block("cid").alias("cblk"), "rid", "cid", "val").repartition(n, "rblk", "cblk"))


def chunk_overlay(a: DataFrame, b: DataFrame, f: MergeFn) -> DataFrame:
    """A direct overlay of two chunked matrices: aligned chunks meet where they lie."""
    x, y = a.withColumnRenamed("val", "av"), b.withColumnRenamed("val", "bv")
    both = x.join(y, ["rblk", "cblk", "rid", "cid"], "full")
    zero = lambda c: F.coalesce(c, F.lit(0.0))
    return both.select("rid", "cid", f(zero("av"), zero("bv")).alias("val"))


def cross_overlay(a: Matrix, b: Matrix, f: MergeFn) -> DataFrame:
    """A transpose overlay as all pairs that are filtered afterwards: chunks of a and of b turned are not aligned."""
    x = a.cells().select(F.col("rid").alias("ar"), F.col("cid").alias("ac"), F.col("val").alias("av"))
    y = b.cells().select(F.col("rid").alias("br"), F.col("cid").alias("bc"), F.col("val").alias("bv"))
    both = x.crossJoin(y).filter((F.abs(F.col("ar") - F.col("bc")) < 1) & (F.abs(F.col("ac") - F.col("br")) < 1))
    return both.select(F.col("ar").alias("rid"), F.col("ac").alias("cid"), f(F.col("av"), F.col("bv")).alias("val"))
