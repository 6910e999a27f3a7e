"""Matrices from SQL: table functions over TABLE arguments, and a data source of generated matrices."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import udtf


class _MatrixAgg:
    """Running aggregate of one line; Spark deals the lines with PARTITION BY."""

    def __init__(self):
        self.n = self.nnz = 0
        self.total, self.best, self.least = 0.0, None, None

    def eval(self, row, fn):
        v = row["val"]
        self.fn = fn
        if v is None:
            return
        self.n += 1
        self.nnz += v != 0
        self.total += v
        self.best = v if self.best is None else max(self.best, v)
        self.least = v if self.least is None else min(self.least, v)

    def terminate(self):
        if self.n:
            yield ({"sum": self.total, "nnz": float(self.nnz), "avg": self.total / self.nnz if self.nnz else None, "max": self.best, "min": self.least}[self.fn],)


class _ExplodeTile:
    def eval(self, row):
        import numpy as np

        from gridalg.operators.tiles import unpack

        x = unpack(row["fmt"], row["nr"], row["nc"], row["ptr"], row["idx"], row["vals"])
        for i, j in zip(*(k.tolist() for k in np.nonzero(x)), strict=True):
            yield row["rblk"], row["cblk"], i, j, float(x[i, j])


class GeneratedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n = int(options.get("n", 100))
        self.density = float(options.get("density", 1.0))
        self.parts = int(options.get("parts", 4))
        self.seed = int(options.get("seed", 1))

    def partitions(self):
        step = -(-self.n // self.parts)
        return [InputPartition((i, min(i + step, self.n))) for i in range(0, self.n, step)]

    def read(self, partition) -> Iterator[tuple]:
        import numpy as np

        lo, hi = partition.value
        for r in range(lo, hi):
            rng = np.random.default_rng((self.seed, r))
            k = self.n if self.density >= 1 else rng.binomial(self.n, self.density)
            for c in np.sort(rng.choice(self.n, k, replace=False)).tolist():
                yield r, c, float(rng.uniform(0.001, 1))


class Generated(DataSource):
    """Uniform sparse (density below 1) or dense square matrices: options n, density, parts, seed."""

    @classmethod
    def name(cls) -> str:
        return "generated_matrix"

    def schema(self) -> str:
        return "rid long, cid long, val double"

    def reader(self, schema) -> GeneratedReader:
        return GeneratedReader(self.options)


def register(spark: SparkSession) -> None:
    """SQL names: matrix_agg(TABLE(cells) PARTITION BY (rid), 'sum'), explode_tile(TABLE(tiles)); format generated_matrix.

    matrix_agg is a convenience of one Python call a row; Matrix.agg and plain SQL aggregates stay in the JVM.
    """
    spark.udtf.register("matrix_agg", udtf(_MatrixAgg, returnType="val double"))
    spark.udtf.register("explode_tile", udtf(_ExplodeTile, returnType="rblk long, cblk long, i int, j int, val double"))
    spark.dataSource.register(Generated)
