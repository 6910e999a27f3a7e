import numpy as np
import pytest
from pyspark.sql import functions as F

from gridalg.algos import pnmf as nmf, regress
from gridalg.algos.regress import linreg, linreg_row, qr
from gridalg.api import CID, NULL, RID, VAL, Engine, Limits, Matrix, Scheme, TooLarge
from gridalg.functions.encode import dense_codes
from gridalg.operators import tiles
from gridalg.sources import store
from gridalg.sources.adapters import from_json_number, from_links, from_table
from tests.support import array, matrix

R = np.random.default_rng(3)


def test_null_zero_and_absent(spark):
    cells = spark.createDataFrame([(0, 0, None), (0, 1, 0.0), (1, 1, 5.0)], "rid long, cid long, val double")
    m = Matrix.of(cells, 3, 3, nullable=True)
    assert m.agg("nnz", "a").scalar() == 1 and m.row_sums().cells().orderBy("rid").collect()[0].val == 0
    assert m.agg("min", "a").scalar() == 0
    high = m.select(VAL > 1)
    assert high.node.absent == NULL and [tuple(r) for r in high.cells().collect()] == [(1, 1, 5.0)]
    low = m.select(VAL < 1)  # zeros meet it: losers become NULL, absent ones stay zeros
    assert low.node.absent == "zero" and {(r.rid, r.cid): r.val for r in low.cells().collect()} == {(0, 0): None, (0, 1): 0.0, (1, 1): None}
    assert {r.rid for r in m.select_nonempty_rows().cells().collect()} == {0, 1}
    assert Matrix.of(cells.filter("rid = 1"), 3, 3, absent=NULL).agg("max", "a").scalar() == 5
    assert (m + m).cells().filter("rid = 0 AND cid = 0").first().val is None


def test_division(spark):
    a, b = np.array([[1.0, 0.0, 6.0]]), np.array([[2.0, 5.0, 0.0]])
    got = {r.cid: r.val for r in (matrix(spark, a) / matrix(spark, b)).cells().collect()}
    assert got == {0: 0.5, 2: None}


def test_elementwise_with_absent_nulls(spark):
    a = Matrix.of(spark.createDataFrame([(0, 0, 2.0)], "rid long, cid long, val double"), 1, 2, absent=NULL)
    b = matrix(spark, [[0.0, 3.0]])
    assert [tuple(r) for r in (a * b).cells().collect()] == [(0, 0, 0.0)]
    assert [tuple(r) for r in (a + matrix(spark, [[1.0, 3.0]])).cells().collect()] == [(0, 0, 3.0)]


def test_selections_keep_ids_and_reindex(spark):
    x = R.integers(0, 5, (6, 4)).astype(float)
    x[2] = 0
    m = matrix(spark, x)
    assert np.array_equal(array(m.rows(1, 3).cols(0, 1)), np.where((np.arange(6)[:, None] >= 1) & (np.arange(6)[:, None] <= 3) & (np.arange(4)[None] <= 1), x, 0))
    r = m.select_nonempty_rows().reindex()
    assert np.array_equal(array(r), x[x.any(1)])
    ids = spark.createDataFrame([(1,), (4,)], "i long")
    assert {c.rid for c in m.rows_in(ids).cells().collect()} == {i for i in (1, 4) if x[i].any()}
    assert np.array_equal(array(m.select((VAL > 1) | ~(CID == 0)).select(RID != 1)), np.where(((x > 1) | (np.arange(4)[None] != 0)) & (np.arange(6)[:, None] != 1), x, 0))
    parts = m.kfold(3, seed=1)
    assert sum(t.cells().count() for _, t in parts) == np.count_nonzero(x)
    assert all(a.cells().count() + b.cells().count() == np.count_nonzero(x) for a, b in parts)


def test_least_squares_and_qr(spark):
    x, y = R.normal(size=(30, 3)), R.normal(size=(30, 1))
    mx, my = matrix(spark, x), matrix(spark, y)
    want = np.linalg.lstsq(x, y, rcond=None)[0]
    assert np.allclose(array(linreg(mx, my)), want)
    assert np.allclose(array(linreg_row(mx, my, 1))[1], want[1])
    q, r = qr(mx)
    assert np.allclose(array(q) @ array(r), x) and np.allclose(array(q).T @ array(q), np.eye(3))
    with pytest.raises(TooLarge):
        linreg(mx.using(Engine(limits=Limits(inverse=2))), my).cells()


def test_factorisation(spark):
    x = R.poisson(1.0, (12, 9)).astype(float)
    x[4] = 0
    a = matrix(spark, x)
    f1 = nmf.step_w(a, nmf.start(a, 3))
    w, h = (array(m) for m in nmf.matrices(a, f1))
    keep = x.any(1)
    assert np.allclose((w @ h).sum(1)[keep], x.sum(1)[keep])  # after the first half step row sums agree
    f, history = nmf.pnmf(a, 3, iterations=4)
    assert all(p >= q - 1e-9 for p, q in zip(history, history[1:], strict=False))
    w, h = (array(m) for m in nmf.matrices(a, f))
    assert np.isfinite(w).all() and np.isfinite(h).all()
    at = x > 0
    assert history[-1] == pytest.approx((w @ h).sum() - (x[at] * np.log((w @ h)[at])).sum())
    cols = x.any(0)
    assert np.allclose((w @ h).sum(0)[cols], x.sum(0)[cols])


def test_steps_by_grid_nonzeros_and_full_product_agree(spark):
    x = R.poisson(0.6, (40, 25)).astype(float)
    x[3], x[:, 2] = 5, 0  # a heavy row, an empty column
    a = matrix(spark, x)
    f = nmf.start(a, 3)
    results = []
    for one in (nmf.step(a, f), nmf.step(a, f, nmf.Grid.of(a.cells(), 9)), nmf.step(a, f, nmf.Grid.of(a.cells(), 1)), nmf.step_full(a, f)):
        results.append([array(m) for m in nmf.matrices(a, one)])
    for w, h in results[1:]:
        assert np.allclose(w, results[0][0]) and np.allclose(h, results[0][1])
    grid = nmf.Grid.of(a.cells(), 9)
    rows = {r.part: r.n for r in grid.cells.groupBy("part").agg(F.count("*").alias("n")).collect()}
    assert grid.side == 3 and len(rows) == 9 and max(rows.values()) < np.count_nonzero(x) / 3
    assert nmf.prepare(matrix(spark, x, stats=True), 3) is not None and nmf.prepare(matrix(spark, np.eye(30), stats=True), 3) is None


def test_recommendations_against_numpy(spark):
    y, x = R.poisson(0.7, (14, 9)).astype(float), np.abs(R.normal(size=(14, 4))).round(2)
    y[:, 4], x[:, 1] = 0, 0  # a user without ratings, a feature without entries
    both = np.hstack([y, np.divide(x, x.max(0), out=np.zeros_like(x), where=x.max(0) > 0)])
    k = 3
    w = np.array([[((7 * i + 3 * j) % 11 + 1) / 11 for j in range(k)] for i in range(14)])
    h = np.array([[((3 * i + 7 * j) % 11 + 1) / 11 for i in range(13)] for j in range(k)])
    for _ in range(5):
        w = w * (np.where(both, both / (w @ h), 0) @ h.T) / h.sum(1)
        h = h * (w.T @ np.where(both, both / (w @ h), 0)) / w.sum(0)[:, None]
    want = {}
    for u in np.flatnonzero(y.any(0)).tolist():
        score = sorted(((-float(w[i] @ h[:, u]), i) for i in range(14) if not y[i, u]))[:4]
        want[u] = [(r + 1, i, pytest.approx(-s)) for r, (s, i) in enumerate(score)]
    for sizes in ((1000, 10_000), (2, 3)):
        nmf.USERS, nmf.ITEMS = sizes
        got = {}
        for r in nmf.recommend(matrix(spark, y), matrix(spark, x), k, 4).collect():
            got.setdefault(r.user, []).append((r["rank"], r["item"], r.val))
        assert {u: sorted(v) for u, v in got.items()} == want
    nmf.USERS, nmf.ITEMS = 1000, 10_000


def test_qr_by_a_tree(spark, monkeypatch):
    monkeypatch.setattr(regress, "FAN", 2)
    x = R.normal(size=(60, 5))
    m = Matrix.of(matrix(spark, x).cells(), 60, 5)
    q, r = (array(t) for t in regress.qr(m))
    assert np.allclose(q @ r, x) and np.allclose(q.T @ q, np.eye(5)) and (np.diag(r) > 0).all() and np.allclose(r, np.triu(r))


def test_tiles(spark):
    x, y = R.integers(0, 3, (10, 7)).astype(float), R.integers(0, 3, (7, 11)).astype(float)
    x[:4] = np.where(R.uniform(size=(4, 7)) < 0.9, 0, x[:4])
    for side in (3, 4, 16):
        t = tiles.to_tiles(matrix(spark, x).cells(), 10, 7, side)
        assert np.array_equal(array(Matrix.of(tiles.to_cells(t, side), 10, 7)), x)
        assert np.array_equal(array(Matrix.of(tiles.to_cells(tiles.transpose(t), side), 7, 10)), x.T)
        p = tiles.multiply(t, tiles.to_tiles(matrix(spark, y).cells(), 7, 11, side))
        assert np.array_equal(array(Matrix.of(tiles.to_cells(p, side), 10, 11)), x @ y)
    for fmt in (0, 1, 2):
        assert np.array_equal(tiles.unpack(**tiles.pack(x, fmt)), x)
    cells = tiles.tensor_tiles(matrix(spark, x).cells(), matrix(spark, x).cells(), ("rid", "rid"), 3).select("d1", "b2", "b3", F.inline("tile")).collect()
    assert sum(r.val for r in cells) == pytest.approx(sum(row.sum() ** 2 for row in x))


def test_aligned_placement_adds_no_exchange(spark):
    x = R.uniform(1, 2, (9, 9))
    m = matrix(spark, x).placed(Scheme.R)
    plan = m.row_sums().cells()._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1
    other = matrix(spark, x).placed(Scheme.C)
    assert other.row_sums().cells()._jdf.queryExecution().executedPlan().toString().count("Exchange") == 2


def test_trace_of_gram_is_one_scan(spark):
    m = matrix(spark, R.uniform(size=(5, 4)))
    plan = (m.T @ m).trace().cells()._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan
    # selections reach the inputs of a product and leave no filter above the join
    entry = (m.T @ m).entry(1, 2).cells()._jdf.queryExecution().optimizedPlan().toString()
    assert entry.index("Join") < entry.index("Filter")


def test_store_and_readers(spark, tmp_path):
    x = R.integers(0, 3, (6, 5)).astype(float)
    m = matrix(spark, x)
    store.write(m, str(tmp_path / "m"), rows_per_bucket=2)
    back = store.read(spark, str(tmp_path / "m"))
    assert np.array_equal(array(back), x) and back.node.meta.nnz == np.count_nonzero(x)
    (tmp_path / "g.txt").write_text("# edges\n1 2\n1 2\n3 1 0.5\n\n")
    assert {tuple(r) for r in store.read_triples(spark, str(tmp_path / "g.txt"), base=1).collect()} == {(0, 1, 2.0), (2, 0, 0.5)}
    u = store.uniform(spark, 200, 0.01)
    assert 300 < u.cells().count() <= 400 and store.dense(spark, 5).cells().count() == 25


def test_codes_and_adapters(spark):
    words = spark.createDataFrame([("b",), ("a",), (None,), ("c",), ("a",)], "w string")
    codes, n = dense_codes(words)
    assert n == 3 and {tuple(r) for r in codes.collect()} == {("a", 0), ("b", 1), ("c", 2)}
    assert dense_codes(words.filter("w = 'z'"))[1] == 0
    t = spark.createDataFrame([(1, 2, 3.0), (1, 2, 4.0), (None, 1, 1.0)], "a int, b int, v double")
    assert [tuple(r) for r in from_table(t, "a", "b", "v").collect()] == [(1, 2, 7.0)]
    j = spark.createDataFrame([(1, '{"k": 2}'), (1, '{"k": 3}'), (2, "{}")], "i long, p string")
    assert [tuple(r) for r in from_json_number(j, "i", "p", "k").collect()] == [(1, 0, 5.0)]
    h = spark.createDataFrame([(0, '<a href="/x">x</a><a href="/x">y</a><a href="http://z">z</a>')], "i long, h string")
    cells, n = from_links(h, "i", "h")
    assert n == 1 and cells.first().val == 2


def test_top_and_views(spark):
    m = matrix(spark, [[1.0, 3.0, 3.0], [0.0, 2.0, 0.0]])
    assert {tuple(r) for r in m.top(2).collect()} == {(0, 1, 1, 3.0), (0, 2, 2, 3.0), (1, 1, 1, 2.0)}
    m.create_view("some_cells")
    assert spark.sql("SELECT sum(val) FROM some_cells").first()[0] == 9


def test_baselines_and_measures(spark):
    from gridalg import baselines, measure
    from gridalg.functions.merge import ADD, MUL

    x = R.integers(0, 3, (8, 5)).astype(float)
    m = matrix(spark, x)
    g = x.T @ x
    assert baselines.product_first(m, "sum", "d").first().val == np.trace(g)
    assert baselines.dense_blocks(m, "sum", "d", 3) == np.trace(g)
    assert {(r.rid, r.val) for r in baselines.rdd_rowsum(m).collect()} == {(i, v) for i, v in enumerate(g.sum(1)) if x[:, i].any()}
    want = {tuple(r) for r in m.join(m, "rid=rid", MUL).cells.collect() if r[-1]}
    assert {tuple(r) for r in baselines.cross_then_filter(m, m, ("rid", "rid"), MUL).collect() if r[-1]} == want
    y = R.integers(0, 3, (8, 5)).astype(float)
    other = matrix(spark, y)
    chunks = baselines.chunk_overlay(baselines.chunked(m, 3), baselines.chunked(other, 3), ADD)
    assert np.array_equal(array(Matrix.of(chunks, 8, 5)), x + y)
    assert np.array_equal(array(Matrix.of(baselines.cross_overlay(m, other.T, MUL), 8, 5)), x * y)
    assert {tuple(r) for r in baselines.hashed(m).join(baselines.hashed(m), "rid=rid", MUL).cells.collect() if r[-1]} == want
    assert measure.timed(lambda: m.cells(), 1) > 0
    assert measure.shuffled(spark, lambda: m.row_sums().cells())[0] > 0
    assert measure.outcome(lambda: m.cells(), spark)[0] == "done"
    assert min(measure.split(lambda: m.cells(), lambda df: df.filter("val > 1"))) > 0


def test_stream_gives_what_the_batch_gives(spark, tmp_path):
    from gridalg.streaming import windows
    from tests.support import DATA

    events = spark.read.parquet(f"{DATA}/events.parquet")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = windows.event_stream(spark, str(tmp_path / "in"))
    q = windows.running_row_sums(stream).writeStream.outputMode("update").format("memory").queryName("sums").option("checkpointLocation", str(tmp_path / "c1")).start()
    q.processAllAvailable()
    q.stop()
    last = {r.rid: (r.val, r.n) for r in spark.sql("SELECT rid, max_by(val, n) AS val, max(n) AS n FROM sums GROUP BY rid").collect()}
    want = {r.user_id: (r.v, r.n) for r in events.groupBy("user_id").agg(F.sum("value").alias("v"), F.count("*").alias("n")).collect()}
    assert last.keys() == want.keys() and all(last[k][1] == want[k][1] and last[k][0] == pytest.approx(want[k][0]) for k in want)
    w = windows.windowed(stream, "1 day", "60 days").writeStream.outputMode("complete").format("memory").queryName("days").option("checkpointLocation", str(tmp_path / "c2")).start()
    w.processAllAvailable()
    w.stop()
    assert spark.sql("SELECT sum(n) AS n FROM days").first().n == events.count()
    s = windows.sessions(events).groupBy().agg(F.sum("n")).first()[0]
    assert s == events.count()


def test_tiles_of_a_batch_are_made_at_once(spark):
    x = np.where(R.uniform(size=(30, 23)) < 0.3, R.integers(1, 9, (30, 23)), 0).astype(float)
    x[:8, :8] = 1  # dense blocks among sparse ones
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    try:
        for batch in (1, 7, 10_000):  # blocks that go on over batches, and many blocks in one
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", batch)
            for side in (1, 4, 64):
                t = tiles.to_tiles(matrix(spark, x).cells(), 30, 23, side)
                rows = t.collect()
                assert len({(r.rblk, r.cblk) for r in rows}) == len(rows)
                for r in rows:
                    own = x[r.rblk * side : (r.rblk + 1) * side, r.cblk * side : (r.cblk + 1) * side]
                    assert own.any() and {"rblk": r.rblk, "cblk": r.cblk} | tiles.pack(own) == r.asDict()
                assert np.array_equal(array(Matrix.of(tiles.to_cells(t, side), 30, 23)), x)
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    assert "InPandas" not in t._jdf.queryExecution().executedPlan().toString()  # no call of Python for each block


def test_recommendation_bounds_lose_nothing(monkeypatch):
    for kind in ("uniform", "ties", "signed"):
        w, h = R.random((3000, 4)), R.random((60, 4))
        if kind == "ties":
            w, h = w.round(1), h.round(1)
            h[:5], w[:5] = 0, 0
        elif kind == "signed":
            w, h = w - 0.5, h - 0.5
        full = nmf._scores(h, w)
        row, had = np.nonzero((R.random(full.shape) < 0.02) | (full > np.sort(full, axis=1)[:, -4:-3]))  # the best are seen
        full[row, had] = -np.inf
        want = np.argsort(-full, axis=1, kind="stable")[:, :5]
        for sizes in ((16, 8, 2, 3), (256, 256, 16, 64)):
            for name, size in zip(("LEAF", "GROUP", "FIRST", "ROUND"), sizes, strict=True):
                monkeypatch.setattr(nmf, name, size)
            at, val = nmf._search(h, row, had, w, 5)
            assert np.array_equal(at, want) and np.array_equal(val, np.take_along_axis(full, want, 1))
    few, val = nmf._search(h[:2], np.array([0, 0, 1]), np.array([0, 1, 2]), w[:3], 5)
    assert np.isfinite(val).sum(1).tolist() == [1, 2]


def test_recommendation_scores_few_items(monkeypatch):
    w, h = R.random((20_000, 4)), R.random((300, 4))
    scored, scores = [], nmf._scores
    monkeypatch.setattr(nmf, "_scores", lambda a, b: scored.append(len(a) * len(b)) or scores(a, b))
    none = np.zeros(0, np.int64)
    nmf._search(h, none, none, w, 5)
    assert sum(scored) < len(h) * len(w) / 2


def test_recommendation_needs_no_objective(spark, monkeypatch):
    monkeypatch.setattr(nmf, "objective", None)
    y = R.poisson(0.7, (6, 5)).astype(float)
    assert nmf.recommend(matrix(spark, y), matrix(spark, np.ones((6, 2))), 2, 2, 1).count() > 0
