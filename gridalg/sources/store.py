"""Files of entries: Parquet with its catalog entry, text triples, and generated matrices."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from gridalg.api import Engine, Matrix
from gridalg.catalog import MatrixMeta, measured
from gridalg.plans.nodes import Source


def write(m: Matrix, path: str, rows_per_bucket: int = 1_000_000) -> None:
    """Entries in folders by range of rows (so that row selections prune files), and the catalog entry beside them."""
    cells = m.cells()
    meta = measured(cells, MatrixMeta(*m.shape, absent=m.node.absent))
    cells.withColumn("rb", F.floor(F.col("rid") / rows_per_bucket)).repartition("rb").write.mode("overwrite").partitionBy("rb").parquet(f"{path}/cells")
    m.spark.createDataFrame([(meta.json(),)], "meta string").coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")


def read(spark: SparkSession, path: str, engine: Engine = Engine()) -> Matrix:
    meta = MatrixMeta.parse(spark.read.parquet(f"{path}/meta").first()[0])
    cells = spark.read.parquet(f"{path}/cells").select("rid", "cid", "val")
    return Matrix(Source(cells, meta, path), spark, engine)


def write_bucketed(m: Matrix, table: str, buckets: int, by: str = "rid") -> None:
    """A table that keeps the placement by row or column, so that later joins and aggregates need no exchange."""
    m.cells().write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def read_triples(spark: SparkSession, path: str, base: int = 0, sep: str = r"\s+") -> DataFrame:
    """Lines 'i j v' or 'i j' (then v is 1), such as edge lists and coordinate files; lines that start with # or % are skipped."""
    parts = F.split(F.trim("value"), sep)
    lines = spark.read.text(path).filter(~F.col("value").rlike(r"^\s*([#%]|$)"))
    cells = lines.select((parts[0].cast("long") - base).alias("rid"), (parts[1].cast("long") - base).alias("cid"), F.coalesce(F.get(parts, 2).try_cast("double"), F.lit(1.0)).alias("val"))
    return cells.groupBy("rid", "cid").agg(F.sum("val").alias("val"))


def uniform(spark: SparkSession, n: int, density: float, seed: int = 1) -> Matrix:
    """A sparse n x n matrix with about density * n * n entries at uniform places."""
    k = round(density * n * n)
    h = lambda s: F.pmod(F.xxhash64("id", F.lit(seed * 10 + s)), F.lit(n))
    cells = spark.range(k).select(h(1).alias("rid"), h(2).alias("cid"), (F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1000)) / 1000 + 0.001).alias("val"))
    return Matrix.of(cells.groupBy("rid", "cid").agg(F.max("val").alias("val")), n, n, name=f"u{n}")


def dense(spark: SparkSession, n: int, seed: int = 1) -> Matrix:
    from gridalg.operators.cells import grid

    cells = grid(spark, n, n, n * n).withColumn("val", F.pmod(F.xxhash64("rid", "cid", F.lit(seed)), F.lit(1000)) / 1000 + 0.001)
    return Matrix.of(cells, n, n, name=f"d{n}")
