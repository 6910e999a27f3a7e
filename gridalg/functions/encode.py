"""Dictionaries from values to dense codes."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from gridalg.functions.lineage import cut


def dense_codes(values: DataFrame) -> tuple[DataFrame, int]:
    """(value, code): distinct non-null values of the only column numbered from 0 in their order, and how many.

    Values are dealt by range; a partition's codes start where the sizes of those before end. The driver sees one
    number a partition. The sorted values are written first, so that both reads see the same order.
    """
    name = values.columns[0]
    sorted_ = values.filter(F.col(name).isNotNull()).distinct().repartitionByRange(name).sortWithinPartitions(name)
    placed = cut(sorted_.select(name, F.spark_partition_id().alias("__p"), (F.monotonically_increasing_id() % F.lit(1 << 33)).alias("__i")))
    sizes = dict(placed.groupBy("__p").count().collect())
    start, total = {}, 0
    for p in sorted(sizes):
        start[p] = total
        total += sizes[p]
    if not start:
        return placed.select(name, F.col("__i").alias("code")), 0
    offset = F.create_map(*[F.lit(x) for pair in start.items() for x in pair])
    return placed.select(name, (F.element_at(offset, F.col("__p")) + F.col("__i")).cast("long").alias("code")), total
