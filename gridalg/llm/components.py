"""Connected components by alternating star contractions, all on the cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from gridalg.llm.lineage import cut


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """node, component (smallest node reachable) for each node of links(a, b).

    Each round hangs the larger neighbours of a node, then the smaller ones, on the smallest; the edge set never
    grows, and forests of depth d end after about log d rounds. A round deals the edges twice by one end, and every
    edge says whether it was moved: when none was, all is done. The driver sees one row a round.
    Empty links give an empty result; self-links and repeated links do no harm.
    """
    edges = links.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = F.min("b").over(Window.partitionBy("a"))
    for _ in range(rounds):
        both = edges.select(F.inline(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))))
        large = both.withColumn("m", F.least("a", low)).filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"), (F.col("m") < F.col("a")).alias("moved"))
        small = large.repartition("a").groupBy("a", "b").agg(F.max("moved").alias("moved")).withColumn("m", low)
        lowest = F.col("b") == F.col("m")
        edges = cut(small.select(F.when(lowest, F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b"), (F.col("moved") | ~lowest).alias("moved")))
        if edges.filter("moved").isEmpty():
            break
    else:
        raise RuntimeError(f"no fixpoint after {rounds} rounds")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
