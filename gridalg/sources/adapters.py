"""Entries from tables, arrays, tokens, features, json and links. Every adapter ends in one aggregate, so entries are unique."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from gridalg.functions.encode import dense_codes


def from_table(df: DataFrame, row: str | Column, col: str | Column, val: str | Column | None = None, agg: str = "sum") -> DataFrame:
    """rid, cid, val: an aggregate of val (a count without val) for each pair of ids."""
    c = lambda x: F.expr(x) if isinstance(x, str) else x
    value = F.count("*") if val is None else {"sum": F.sum, "max": F.max, "min": F.min, "avg": F.avg, "count": F.count}[agg](F.col("__v"))
    keyed = df.select(c(row).cast("long").alias("rid"), c(col).cast("long").alias("cid"), *([] if val is None else [c(val).cast("double").alias("__v")]))
    return keyed.filter("rid IS NOT NULL AND cid IS NOT NULL").groupBy("rid", "cid").agg(value.cast("double").alias("val"))


def from_coded(df: DataFrame, row: str, text: str) -> tuple[DataFrame, int]:
    """Counts of (row id, text), texts coded in their order; also the number of codes."""
    codes, n = dense_codes(df.select(F.col(text).alias("__t")))
    return from_table(df.join(codes, F.col(text) == F.col("__t")), row, "code"), n


def from_arrays(df: DataFrame, row: str, array: str) -> DataFrame:
    """Elements of an array column: cid is the position."""
    return df.select(F.col(row).cast("long").alias("rid"), F.posexplode(array).alias("p", "v")).select("rid", F.col("p").cast("long").alias("cid"), F.col("v").cast("double").alias("val"))


def from_tokens(df: DataFrame, row: str, text: str) -> tuple[DataFrame, int]:
    """Counts of the words between single blanks, coded in their order; also the number of codes."""
    return from_coded(df.select(F.col(row).alias("__r"), F.explode(F.split(text, " ")).alias("token")), "__r", "token")


def from_features(df: DataFrame, row: str, features: list[Column]) -> DataFrame:
    """One column of the matrix for each expression; NULLs are not stored."""
    pairs = F.array(*[F.struct(F.lit(i).cast("long").alias("cid"), f.cast("double").alias("val")) for i, f in enumerate(features)])
    return df.select(F.col(row).cast("long").alias("rid"), F.inline(pairs)).filter("val IS NOT NULL")


def from_json_number(df: DataFrame, row: str, json: str, key: str, cid: int = 0) -> DataFrame:
    """A number in a json text as one column, summed over the rows of an id."""
    value = F.get_json_object(F.col(json), f"$.{key}").cast("double")
    return df.select(F.col(row).cast("long").alias("rid"), value.alias("v")).filter("v IS NOT NULL").groupBy("rid").agg(F.sum("v").alias("val")).select("rid", F.lit(cid).cast("long").alias("cid"), "val")


def from_links(df: DataFrame, row: str, html: str) -> tuple[DataFrame, int]:
    """Counts of the local paths that a page links to, coded in their order; also the number of codes."""
    links = df.select(F.col(row).alias("__r"), F.explode(F.regexp_extract_all(F.col(html), F.lit('href="(/[^"]*)"'), F.lit(1))).alias("path"))
    return from_coded(links, "__r", "path")
