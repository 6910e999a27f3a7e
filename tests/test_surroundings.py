import numpy as np
import pytest
from pyspark.sql import functions as F

from gridalg.api import Matrix
from gridalg.functions.merge import MUL
from gridalg.operators import bloom, events, tiles
from gridalg.operators.cells import PRODUCTS
from tests.support import array, matrix

R = np.random.default_rng(12)


@pytest.mark.parametrize("strategy", PRODUCTS)
def test_product_strategies_agree(spark, strategy):
    x, y = R.integers(0, 3, (6, 5)).astype(float), R.integers(0, 3, (5, 7)).astype(float)
    assert np.array_equal(array(matrix(spark, x).matmul(matrix(spark, y), strategy)), x @ y)


def test_heavy_ids_are_split(spark):
    from gridalg.operators.joins import Operand, join_salted

    x, y = R.integers(0, 3, (30, 3)).astype(float), R.integers(0, 3, (3, 9)).astype(float)
    a, b = matrix(spark, x), matrix(spark, y)
    assert np.array_equal(array(a.matmul(b, "salted", heavy=4)), x @ y)
    want = {tuple(r) for r in a.join(b, "cid=rid", MUL).cells.collect()}
    got = {tuple(r) for r in join_salted(Operand(a.cells(), 30, 3), Operand(b.cells(), 3, 9), "cid=rid", MUL, heavy=4).collect()}
    assert got == want


def test_unknown_product_strategy(spark):
    with pytest.raises(ValueError):
        matrix(spark, [[1.0]]).matmul(matrix(spark, [[1.0]]), "guess")


def test_dense_averages_largest_entries_and_outliers(spark):
    x = np.array([[4.0, 0.0, 8.0, 8.0], [0.0, 1.0, 0.0, 0.0]])
    m = matrix(spark, x)
    assert np.array_equal(array(m.avg_dense("r")).ravel(), x.mean(1)) and np.array_equal(array(m.avg_dense("c")).ravel(), x.mean(0))
    assert {tuple(r) for r in m.argmax().collect()} == {(0, 2, 8.0), (1, 1, 1.0)}
    y = np.ones((1, 30))
    y[0, 7] = 50
    assert [r.cid for r in matrix(spark, y).outliers(3).collect()] == [7]


def test_block_filters_lose_no_match(spark):
    x, y = R.integers(0, 40, (20, 18)).astype(float), R.integers(30, 200, (15, 22)).astype(float)
    a, b = matrix(spark, x), matrix(spark, y)
    want = {tuple(r)[:4] for r in a.join(b, "val=val", MUL).cells.collect() if r[-1]}
    assert {tuple(r)[:4] for r in bloom.block_join(a.cells(), b.cells(), 5).collect()} == want
    far = matrix(spark, y + 1000)
    assert bloom.block_pairs(matrix(spark, x[:2, :2]).cells(), far.cells(), 50).count() <= 1


def test_sql_functions_and_generated_matrices(spark):
    from gridalg import sqlapi

    sqlapi.register(spark)
    x = R.integers(-2, 3, (5, 4)).astype(float)
    matrix(spark, x).create_view("udtf_cells")
    for fn, want in (("sum", x.sum(1)), ("nnz", (x != 0).sum(1))):
        got = sorted(r.val for r in spark.sql(f"SELECT val FROM matrix_agg(TABLE(udtf_cells) PARTITION BY (rid), '{fn}')").collect())
        assert got == sorted(v for v, row in zip(want, x, strict=True) if row.any())
    tiles.to_tiles(matrix(spark, x).cells(), 5, 4, 3).createOrReplaceTempView("udtf_tiles")
    cells = spark.sql("SELECT * FROM explode_tile(TABLE(udtf_tiles))").collect()
    assert {(r.rblk * 3 + r.i, r.cblk * 3 + r.j): r.val for r in cells} == {(i, j): v for (i, j), v in np.ndenumerate(x) if v}
    g = spark.read.format("generated_matrix").option("n", 50).option("density", 0.1).load()
    assert 150 < g.count() < 350 and g.agg(F.count_distinct("rid", "cid")).first()[0] == g.count()
    assert spark.read.format("generated_matrix").option("n", 6).load().count() == 36


def test_joins_on_time(spark):
    left = spark.createDataFrame([(1, 10), (1, 20), (2, 5), (1, 3)], "k int, t int")
    right = spark.createDataFrame([(1, 9, "a"), (1, 20, "b"), (2, 6, "c"), (1, 15, None)], "k int, t int, v string")
    got = {(r.k, r.t): r.v_as_of for r in events.as_of(left, right, "k", "t", "v").collect()}
    assert got == {(1, 10): "a", (1, 20): "b", (2, 5): None, (1, 3): None}
    ts = lambda df: df.withColumn("t", F.col("t").cast("timestamp"))
    spans = spark.createDataFrame([(1, 0, 7300), (1, 7000, 7100), (2, 0, 10)], "k int, a int, b int").select("k", F.col("a").cast("timestamp").alias("a"), F.col("b").cast("timestamp").alias("b"))
    points = ts(spark.createDataFrame([(1, 7050), (1, 7299), (1, 7300), (2, 3), (2, 10)], "k int, t int"))
    got = sorted((r.k, int(r.t.timestamp()), int(r.a.timestamp())) for r in events.within(points, spans, "k", "t", "a", "b").collect())
    base = sorted([(1, 7050, 0), (1, 7050, 7000), (1, 7299, 0), (2, 3, 0)])
    assert got == base
    ranges = spark.createDataFrame([(0.0, 1.5, "low"), (1.0, 9.0, "high")], "lo double, hi double, name string")
    assert events.in_range(matrix(spark, [[1.0, 5.0]]).cells(), ranges).count() == 3


def test_view_of_matrix_is_lazy(spark):
    assert Matrix.ones(spark, 2, 3).total().scalar() == 6
