import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridalg.api import Engine, Limits, Matrix, Scheme, Tensor, TooLarge
from gridalg.functions.merge import ADD, ADD1, LEFTY, MAX, MUL, Flags, MergeFn
from gridalg.operators import joins
from gridalg.operators.bloom import bloom_semijoin, sizing
from gridalg.operators.joins import result_dims
from gridalg.plans.cost import SHAPES, InvalidJoinPredicate, order_of, shape_of
from tests.support import array, matrix

R = np.random.default_rng(9)
A = R.integers(0, 4, (5, 4)).astype(float)
B = R.integers(0, 4, (4, 6)).astype(float)
S = R.integers(0, 3, (4, 4)).astype(float)
T = R.integers(0, 3, (4, 4)).astype(float)
RIGHTY = MergeFn(lambda x, y: y * (x + 1), "righty")
MERGES = {"mul": (MUL, lambda x, y: x * y), "lefty": (LEFTY, lambda x, y: x * (y + 1)), "righty": (RIGHTY, lambda x, y: y * (x + 1)), "add": (ADD, lambda x, y: x + y), "add1": (ADD1, lambda x, y: x + y + 1)}


def brute(a, b, shape, f):
    out = {}
    dims = result_dims(shape)
    for (i, j), x in np.ndenumerate(a):
        for (k, l), y in np.ndenumerate(b):
            va, vb = {"rid": i, "cid": j, "val": x}, {"rid": k, "cid": l, "val": y}
            if all(va[p] == vb[q] for p, q in SHAPES[shape]):
                v = f(x, y)
                if v:
                    out[tuple({"a": va, "b": vb}[s][d] for s, d in dims)] = v
    return out


@pytest.mark.parametrize("shape,name", list(itertools.product(SHAPES, MERGES)))
def test_joins_against_all_pairs(spark, shape, name):
    f, g = MERGES[name]
    a, b = (S, T) if shape in ("overlay", "transpose") else (A, B)
    m = matrix(spark, a).join(matrix(spark, b), shape, f)
    if shape in ("overlay", "transpose"):
        assert np.array_equal(array(m), g(a, b.T if shape == "transpose" else b))
        return
    got = {tuple(r[:-1]): r[-1] for r in m.cells.collect() if r[-1]}
    assert got == brute(a, b, shape, g)
    assert len(m.sizes) == order_of(shape)


@pytest.mark.parametrize("strategy", ["densify", "nested_loop", "bloom", "sparse", "bloom_sparse"])
def test_strategies_agree(spark, strategy):
    a, b = matrix(spark, A), matrix(spark, B)
    want = {tuple(r) for r in a.join(b, "val=val", MUL).cells.collect() if r[-1]}
    assert {tuple(r) for r in a.join(b, "val=val", MUL, strategy=strategy).cells.collect() if r[-1]} == want


def test_probe(spark):
    f = lambda g: MergeFn(g).flags(spark)
    assert f(lambda x, y: x * y) == Flags(True, True, True)
    assert f(lambda x, y: x + y) == Flags(False, False, True)
    assert f(lambda x, y: x * (y + 1)) == Flags(True, False, True)
    assert f(lambda x, y: y * (x - 1)) == Flags(False, True, True)
    assert f(lambda x, y: F.greatest(x, y)) == Flags(False, False, True)
    assert f(lambda x, y: F.try_divide(x, y)) == Flags(False, False, False)
    assert f(lambda x, y: F.lit(0.0)) == Flags(True, True, True)
    assert f(lambda x, y: F.lit(2.0)) == Flags(False, False, False)
    assert MergeFn(lambda x, y: x, declare=Flags(True, False, True)).flags(spark).sx
    assert MAX.flags(spark).z0


def test_illegal_predicates_and_limits(spark):
    for bad in ("rid=rid, rid=cid", "val=val, rid=rid", "nonsense", "rid<rid"):
        with pytest.raises(InvalidJoinPredicate):
            shape_of(bad)
    assert shape_of("RID=RID AND CID=CID") == "overlay" and shape_of((("cid", "rid"), ("rid", "cid"))) == "transpose"
    tight = Engine(limits=Limits(output=10, grid=10))
    a, b = matrix(spark, A, engine=tight), matrix(spark, B)
    for shape, f in (("cross", MUL), ("cid=rid", MUL), ("cid=rid", ADD1)):
        with pytest.raises(TooLarge):
            a.join(b, shape, f).cells  # noqa: B018
    assert a.join(b, "cid=rid", MUL).totals().first().n > 10  # sums need no rows


def test_choices(spark):
    """What the cost model picks on its own, and that all picks give the same rows."""
    a, b = matrix(spark, A, stats=True), matrix(spark, B, stats=True)
    c = a.choose(b, "cid=rid", MUL)
    assert (c.placement.sa, c.placement.sb) == (Scheme.C, Scheme.R) and c.strategy == "auto" and "selectivity" in a.explain_join(b, "cid=rid", MUL)
    big = Matrix.of(spark.range(400).selectExpr("id AS rid", "id % 7 AS cid", "CAST(id AS DOUBLE) AS val"), 400, 7, stats=True, engine=Engine(limits=Limits(broadcast=0)))
    few = Matrix.of(spark.range(0, 400, 50).selectExpr("id AS rid", "0L AS cid", "CAST(id AS DOUBLE) AS val"), 400, 7, stats=True)
    for gamma in ("val=val", "rid=val", "val=rid"):
        x, y = (few.using(big.engine), big) if gamma != "val=rid" else (big, few)
        assert x.choose(y, gamma, MUL).strategy == "bloom_sparse", gamma
        want = sorted(map(tuple, x.join(y, gamma, MUL, strategy="sparse").cells.collect()))
        assert sorted(map(tuple, x.join(y, gamma, MUL).cells.collect())) == want and want
    c = few.choose(big, "val=val", MUL)  # small enough to be sent everywhere
    assert c.strategy == "auto" and c.placement.sa == Scheme.B
    # values of 0 to 399: all whole, 25 of 400 are ids of a dimension of 25
    assert big.node.meta.selectivity(25) == pytest.approx(25 / 400) and big.choose(few, "val=cid", MUL).eta == pytest.approx(7 / 400)
    assert Matrix.of(big.cells(), 400, 7, at_most=500).meta().bound() == 500 and big.measured().meta().nnz == 399


@pytest.mark.parametrize("shape", ["rid=rid", "cid=rid", "rid=val", "val=cid"])
def test_filters_on_ids_and_values(spark, shape):
    a, b = matrix(spark, A), matrix(spark, B)
    for f in (MUL, LEFTY, ADD):
        rows = [{tuple(r) for r in a.join(b, shape, f, strategy=s).cells.collect() if r[-1]} for s in ("auto", "bloom", "bloom_sparse")]
        assert rows[0] == rows[1] == rows[2]
    for bad in ("overlay", "cross"):
        with pytest.raises(ValueError):
            matrix(spark, S).join(matrix(spark, T), bad, MUL, strategy="bloom").cells  # noqa: B018


def test_tensors_select_and_sum_without_their_rows(spark):
    a, b = matrix(spark, A), matrix(spark, B)
    t = a.join(b, "cid=rid", MUL)
    rows = [tuple(r) for r in t.cells.collect()]
    pick = t.select(d1=(1, 2), d3=4)
    assert sorted(map(tuple, pick.cells.collect())) == sorted(r for r in rows if 1 <= r[0] <= 2 and r[2] == 4)
    assert sorted(map(tuple, Tensor(t.cells, t.sizes, t.origin).select(d2=3).cells.collect())) == sorted(r for r in rows if r[1] == 3)
    for over, keep in (("d1", (1, 2)), ("d2", (0, 2)), ("d3", (0, 1))):
        want = {}
        for r in rows:
            k = tuple(r[i] for i in keep)
            want[k] = want.get(k, 0) + r[3]
        plain = a.using(Engine(rules=frozenset())).join(b, "cid=rid", MUL)
        assert {tuple(r)[:2]: r[2] for r in t.agg("sum", (over,)).collect()} == {tuple(r)[:2]: r[2] for r in plain.agg("sum", (over,)).collect()} == want
    assert tuple(t.totals().first()) == (len(rows), sum(r[3] for r in rows))


def test_a_lead_dimension_keeps_aggregates_in_their_tasks(spark):
    wide = lambda x: Matrix.of(matrix(spark, x).cells(), *x.shape, engine=Engine(limits=Limits(broadcast=0)))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        exchanges = lambda df: df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")
        t = wide(A).join(wide(B), "cid=rid", MAX, strategy="sparse")
        assert t.lead(("d2",)) == "d1" and exchanges(t.agg("max", ("d2",))) == exchanges(t.cells)
        laid = t.laid_out(("d1",))
        assert t.lead(("d1",)) == "d2" and exchanges(laid.agg("max", ("d1",))) == exchanges(laid.cells) == exchanges(t.cells) + 1
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_overlay_keeps_one_sided_values(spark):
    assert array(matrix(spark, [[0.0]]).join(matrix(spark, [[2.0]]), "overlay", ADD))[0, 0] == 2


def test_placed_joins_agree(spark):
    a, b = matrix(spark, A, stats=True, engine=Engine(placement=True, limits=Limits(broadcast=0))), matrix(spark, B, stats=True)
    want = {tuple(r) for r in matrix(spark, A).join(b, "cid=rid", MUL).cells.collect()}
    assert {tuple(r) for r in a.join(b, "cid=rid", MUL).cells.collect()} == want


def test_bloom_has_no_false_negatives(spark):
    large = spark.range(5000).selectExpr("id AS rid", "0L AS cid", "CAST(id AS DOUBLE) AS val")
    small = spark.range(0, 5000, 50).selectExpr("id AS rid", "0L AS cid", "CAST(id AS DOUBLE) AS val")
    for fpp in (0.5, 0.01):
        kept = {r.val for r in bloom_semijoin(large, small, fpp).collect()}
        assert {float(x) for x in range(0, 5000, 50)} <= kept
        assert len(kept) < 100 + 4900 * (0.9 if fpp == 0.5 else 0.05)
    assert sizing(10**9, 0.001)[0] == 1 << 26


def test_kron(spark):
    assert np.array_equal(array(matrix(spark, S).kron(matrix(spark, B))), np.kron(S, B))


def test_nested_loop_compares_a_value_once_for_all_its_entries(spark, monkeypatch):
    x = np.array([[1.0, 2, 2, np.inf], [2, 0, 1, 3]])
    y = np.array([[2.0, 2, 5], [np.inf, 1, 2]])
    a, b = matrix(spark, x), matrix(spark, y)
    want = sorted((i, j, k, m, v * u) for (i, j), v in np.ndenumerate(x) for (k, m), u in np.ndenumerate(y) if v and v == u)
    for bunch in (1, 2, 1000):
        monkeypatch.setattr(joins, "BUNCH", bunch)
        got = a.join(b, "VAL=VAL", MUL, strategy="nested_loop").cells.collect()
        assert sorted(map(tuple, got)) == want
    assert joins._bunches(a.cells(), "a", 8).count() == 4  # rows that the loop sees: one for each value, not for each entry
