"""Bloom filters of entry values and ids, in SQL functions."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, functions as F

#: Bits of the largest filter: eight megabytes are broadcast at most, whatever the data.
MAX_BITS = 1 << 26


def sizing(n: int, fpp: float) -> tuple[int, int]:
    """Bits (whole words, at most MAX_BITS) and number of hashes for n values."""
    bits = min(MAX_BITS, max(64, math.ceil(-n * math.log(fpp) / math.log(2) ** 2 / 64) * 64))
    return bits, max(1, min(16, round(bits / max(1, n) * math.log(2))))


def _bit(value: Column, seed: int, bits: int) -> Column:
    # adding zero makes the two zeros one value, as equality does
    return F.pmod(F.xxhash64(value + F.lit(0.0), F.lit(seed)), F.lit(bits))


def words(values: DataFrame, bits: int, hashes: int, key: str = "val") -> DataFrame:
    """One row with the filter of a column as an array of 64-bit words."""
    at = values.select(F.explode(F.array(*[_bit(F.col(key).cast("double"), k, bits) for k in range(hashes)])).alias("bit"))
    word = at.groupBy(F.floor(F.col("bit") / 64).cast("int").alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod("bit", F.lit(64)).cast("int"))).alias("x"))
    found = word.agg(F.map_from_entries(F.collect_list(F.struct("w", "x"))).alias("m"))
    return found.select(F.transform(F.sequence(F.lit(0), F.lit(bits // 64 - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0).cast("long"))).alias("words"))


def bloom_semijoin(large: DataFrame, small: DataFrame, fpp: float = 0.01, expected: int | None = None, keys: tuple[str, str] = ("val", "val")) -> DataFrame:
    """The rows of large whose key may be in small: all that are, and about fpp of the others. keys: that of large, that of small.

    expected is a bound of the different keys of small; without one they are counted first.
    """
    key, other = keys
    small = small.filter(F.col(other).isNotNull())
    n = expected if expected is not None else small.agg(F.approx_count_distinct(other)).first()[0]
    bits, hashes = sizing(max(1, n), fpp)
    probe = large.filter(F.col(key).isNotNull()).crossJoin(F.broadcast(words(small, bits, hashes, other)))
    for k in range(hashes):
        b = _bit(F.col(key).cast("double"), k, bits)
        word = F.get("words", F.floor(b / 64).cast("int"))
        probe = probe.filter(F.getbit(word, F.pmod(b, F.lit(64)).cast("int")) == 1)
    return probe.drop("words")


def block_filters(cells: DataFrame, side: int, bits: int = 1024) -> DataFrame:
    """rblk, cblk, words: one filter of one hash for the nonzero values of each block."""
    keyed = cells.filter("val <> 0").select(F.floor(F.col("rid") / side).alias("rblk"), F.floor(F.col("cid") / side).alias("cblk"), _bit(F.col("val"), 0, bits).alias("bit"))
    word = keyed.groupBy("rblk", "cblk", F.floor(F.col("bit") / 64).cast("int").alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod("bit", F.lit(64)).cast("int"))).alias("x"))
    found = word.groupBy("rblk", "cblk").agg(F.map_from_entries(F.collect_list(F.struct("w", "x"))).alias("m"))
    return found.select("rblk", "cblk", F.transform(F.sequence(F.lit(0), F.lit(bits // 64 - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0).cast("long"))).alias("words"))


def block_pairs(a: DataFrame, b: DataFrame, side: int) -> DataFrame:
    """ar, ac, br, bc: pairs of blocks whose filters share a bit. Blocks are a millionth of the cells at the usual side."""
    x = block_filters(a, side).select(F.col("rblk").alias("ar"), F.col("cblk").alias("ac"), F.col("words").alias("x"))
    y = block_filters(b, side).select(F.col("rblk").alias("br"), F.col("cblk").alias("bc"), F.col("words").alias("y"))
    return x.crossJoin(y).filter(F.exists(F.zip_with("x", "y", lambda p, q: p.bitwiseAND(q)), lambda w: w != 0)).select("ar", "ac", "br", "bc")


def block_join(a: DataFrame, b: DataFrame, side: int) -> DataFrame:
    """ar, ac, br, bc, val of equal nonzero values, block pair by block pair where the filters allow it.

    This is how blocks meet without dealing values anew; joins of entries are cheaper wherever a shuffle by value is.
    """
    pairs = block_pairs(a, b, side).toDF("pr", "pc", "qr", "qc")
    x = a.filter("val <> 0").select(F.col("rid").alias("ar"), F.col("cid").alias("ac"), "val", F.floor(F.col("rid") / side).alias("pr"), F.floor(F.col("cid") / side).alias("pc"))
    y = b.filter("val <> 0").select(F.col("rid").alias("br"), F.col("cid").alias("bc"), "val", F.floor(F.col("rid") / side).alias("qr"), F.floor(F.col("cid") / side).alias("qc"))
    return x.join(pairs, ["pr", "pc"]).join(y, ["qr", "qc", "val"]).select("ar", "ac", "br", "bc", "val")
