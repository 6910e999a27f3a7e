"""The experiment workloads over the given tables, as registered queries with SQL for their results."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from gridalg.algos import pnmf as nmf
from gridalg.algos.regress import cross_validate, gram, linreg_row, qr
from gridalg.api import CID, NULL, RID, VAL, Engine, Matrix, Tensor
from gridalg.functions.encode import dense_codes
from gridalg.functions.merge import ADD, ADD1, LEFTY, MAX, MUL
from gridalg.functions.ship import ship
from gridalg.operators import tiles
from gridalg.operators.bloom import block_join
from gridalg.operators.joins import Operand, join_salted
from gridalg.sources.adapters import from_arrays, from_features, from_links, from_table, from_tokens

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{d}/{name}.parquet")


# stand-in matrices: builder and the SQL of their entries


def _rows(spark: SparkSession, d: str, name: str) -> int:
    """Rows of a table whose keys run from 0: a count that Parquet footers answer."""
    return table(spark, d, name).count()


def _qps(s, d):
    li = table(s, d, "lineitem").select("l_partkey", "l_suppkey", "l_quantity")
    return Matrix.of(from_table(li, "l_partkey", "l_suppkey", "l_quantity"), _rows(s, d, "part"), _rows(s, d, "supplier"), name="QPS", at_most=_rows(s, d, "lineitem"))


def _qcp(s, d):
    both = table(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity").join(table(s, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return Matrix.of(from_table(both, "o_custkey", "l_partkey", "l_quantity"), _rows(s, d, "customer"), _rows(s, d, "part"), name="QCP", at_most=_rows(s, d, "lineitem"))


def _tnn(s, d):
    li = table(s, d, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    both = li.join(table(s, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    both = both.join(table(s, d, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    both = both.join(table(s, d, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return Matrix.of(from_table(both, "c_nationkey", "s_nationkey", "l_quantity"), 25, 25, name="TNN")


def _qol(s, d):
    li = table(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity")
    return Matrix.of(from_table(li, "l_orderkey", "l_linenumber - 1", "l_quantity"), _rows(s, d, "orders"), 7, name="QOL", at_most=_rows(s, d, "lineitem"))


def _users(s, d):
    return (table(s, d, "events").agg(F.max("user_id")).first()[0] or 0) + 1


def _cue(s, d):
    e = table(s, d, "events").select("user_id", "event_type")
    codes, n = dense_codes(e.select("event_type"))
    return Matrix.of(from_table(e.join(codes, "event_type"), "user_id", "code"), _users(s, d), n, name="CUE", at_most=_rows(s, d, "events"))


def _cuh(s, d):
    return Matrix.of(from_table(table(s, d, "events").select("user_id", "ts"), "user_id", "hour(ts)"), _users(s, d), 24, name="CUH", at_most=_rows(s, d, "events"))


def _emb(s, d):
    e = table(s, d, "embeddings")
    return Matrix.of(from_arrays(e, "vec_id", "embedding"), _rows(s, d, "embeddings"), 64, name="EMB")


def _csn(s, d):
    c = table(s, d, "customer").select("c_custkey", "c_mktsegment", "c_nationkey")
    codes, n = dense_codes(c.select("c_mktsegment"))
    return Matrix.of(from_table(c.join(codes, "c_mktsegment"), "c_custkey", "code", "c_nationkey"), _rows(s, d, "customer"), n, name="CSN", at_most=_rows(s, d, "customer"))


def _pfx(s, d):
    p = table(s, d, "part").select("p_partkey", "p_size", "p_retailprice", "p_brand")
    codes, n = dense_codes(p.select("p_brand"))
    own = from_features(p, "p_partkey", [F.lit(1.0), F.col("p_size"), F.col("p_retailprice")])
    brand = p.join(codes, "p_brand").select(F.col("p_partkey").alias("rid"), (F.col("code") + 3).alias("cid"), F.lit(1.0).alias("val"))
    return Matrix.of(own.unionByName(brand), _rows(s, d, "part"), 3 + n, name="PFX", at_most=4 * _rows(s, d, "part"))


def _sxn(s, d):
    return Matrix.of(table(s, d, "supplier").select(F.col("s_suppkey").alias("rid"), F.col("s_nationkey").alias("cid"), F.lit(1.0).alias("val")), _rows(s, d, "supplier"), 25, name="SXN", at_most=_rows(s, d, "supplier"))


def _rxn(s, d):
    return Matrix.of(table(s, d, "nation").select(F.col("n_regionkey").alias("rid"), F.col("n_nationkey").alias("cid"), F.lit(1.0).alias("val")), 5, 25, name="RXN")


def _ctl(s, d):
    c = table(s, d, "conversations").select("conv_id", "turn", "text")
    return Matrix.of(from_table(c, "conv_id", "turn", "length(text)"), None, 8, name="CTL")


def _ylb(s, d):
    lab = table(s, d, "labels")
    return Matrix.of(from_features(lab, "doc_id", [F.col("quality"), F.col("toxic")]), _rows(s, d, "documents"), 2, absent=NULL, name="YLB")


def _ptg(s, d):
    cells, n = from_links(table(s, d, "pages").select("page_id", "html"), "page_id", "html")
    return Matrix.of(cells, _rows(s, d, "pages"), n, name="PTG")


MATRICES = {"QPS": _qps, "QCP": _qcp, "TNN": _tnn, "QOL": _qol, "CUE": _cue, "CUH": _cuh, "EMB": _emb, "CSN": _csn, "PFX": _pfx, "SXN": _sxn, "RXN": _rxn, "CTL": _ctl, "YLB": _ylb, "PTG": _ptg}

_CODE = "(SELECT {k}, row_number() OVER (ORDER BY {k}) - 1 AS code FROM (SELECT DISTINCT {k} FROM {t}))"
SQL = {
    "QPS": "SELECT l_partkey AS rid, l_suppkey AS cid, sum(l_quantity) AS val FROM lineitem GROUP BY 1, 2",
    "QCP": "SELECT o_custkey AS rid, l_partkey AS cid, sum(l_quantity) AS val FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2",
    "TNN": "SELECT CAST(c_nationkey AS BIGINT) AS rid, CAST(s_nationkey AS BIGINT) AS cid, sum(l_quantity) AS val FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2",
    "QOL": "SELECT l_orderkey AS rid, CAST(l_linenumber - 1 AS BIGINT) AS cid, sum(l_quantity) AS val FROM lineitem GROUP BY 1, 2",
    "CUE": f"SELECT user_id AS rid, code AS cid, CAST(count(*) AS DOUBLE) AS val FROM events JOIN {_CODE.format(k='event_type', t='events')} USING (event_type) GROUP BY 1, 2",
    "CUH": "SELECT user_id AS rid, CAST(hour(ts) AS BIGINT) AS cid, CAST(count(*) AS DOUBLE) AS val FROM events GROUP BY 1, 2",
    "EMB": "SELECT vec_id AS rid, CAST(i - 1 AS BIGINT) AS cid, CAST(embedding[i] AS DOUBLE) AS val FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings)",
    "CSN": f"SELECT c_custkey AS rid, code AS cid, CAST(c_nationkey AS DOUBLE) AS val FROM customer JOIN {_CODE.format(k='c_mktsegment', t='customer')} USING (c_mktsegment)",
    "PFX": f"SELECT p_partkey AS rid, CAST(0 AS BIGINT) AS cid, CAST(1 AS DOUBLE) AS val FROM part UNION ALL SELECT p_partkey, 1, p_size FROM part UNION ALL SELECT p_partkey, 2, p_retailprice FROM part UNION ALL SELECT p_partkey, 3 + code, 1 FROM part JOIN {_CODE.format(k='p_brand', t='part')} USING (p_brand)",
    "SXN": "SELECT s_suppkey AS rid, CAST(s_nationkey AS BIGINT) AS cid, CAST(1 AS DOUBLE) AS val FROM supplier",
    "RXN": "SELECT CAST(n_regionkey AS BIGINT) AS rid, CAST(n_nationkey AS BIGINT) AS cid, CAST(1 AS DOUBLE) AS val FROM nation",
    "CTL": "SELECT conv_id AS rid, turn AS cid, CAST(sum(length(text)) AS DOUBLE) AS val FROM conversations GROUP BY 1, 2",
    "YLB": "SELECT doc_id AS rid, CAST(0 AS BIGINT) AS cid, CAST(quality AS DOUBLE) AS val FROM labels UNION ALL SELECT doc_id, 1, toxic FROM labels",
    "PTG": """SELECT page_id AS rid, code AS cid, CAST(count(*) AS DOUBLE) AS val FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages)
        JOIN (SELECT path, row_number() OVER (ORDER BY path) - 1 AS code FROM (SELECT DISTINCT unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages)) USING (path) GROUP BY 1, 2""",
}
NROWS = {"QPS": "(SELECT count(*) FROM part)", "QCP": "(SELECT count(*) FROM customer)", "TNN": "25", "QOL": "(SELECT count(*) FROM orders)", "EMB": "(SELECT count(*) FROM embeddings)", "CUE": "(SELECT max(user_id) + 1 FROM events)", "CUH": "(SELECT max(user_id) + 1 FROM events)"}
NCOLS = {"QPS": "(SELECT count(*) FROM supplier)", "QCP": "(SELECT count(*) FROM part)", "TNN": "25", "QOL": "7", "EMB": "64", "CUE": "5", "CUH": "24"}


def _with(*names: str) -> str:
    return "WITH " + ", ".join(f"{n.lower()} AS ({SQL[n]})" for n in dict.fromkeys(names))


def _exact(df: DataFrame) -> DataFrame:
    return df


def _rounded(df: DataFrame) -> DataFrame:
    """Six digits, so that the order of additions does not show; plus zero, so that -0.0 doesn't either."""
    return df.withColumn("val", F.round("val", 6) + 0.0)


def query(name: str, sql: str | None, rounded: bool = False):
    """Registers a query; a function that gives a matrix or tensor is lowered."""

    def keep(f):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            out = f(spark, sf_dir)
            out = out.cells() if isinstance(out, Matrix) else out.cells if isinstance(out, Tensor) else out
            return _rounded(out) if rounded else out

        QUERIES[name] = run
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def _val(sql: str, rounded: bool) -> str:
    return f"round({sql}, 6) + 0.0" if rounded else sql


# Gram matrices

for _m in ("QPS", "QCP", "EMB", "PTG"):
    _r = _m == "EMB"
    _k = _m.lower()
    query(
        f"gram_rowsum_{_k}",
        f"{_with(_m)}, g AS (SELECT x.cid AS rid, y.cid AS cid, sum(x.val * y.val) AS val FROM {_k} x JOIN {_k} y ON x.rid = y.rid GROUP BY 1, 2) SELECT rid, CAST(0 AS BIGINT) AS cid, {_val('sum(val)', _r)} AS val FROM g GROUP BY rid",
        _r,
    )(lambda s, d, m=_m: gram(MATRICES[m](s, d)).row_sums())
    query(f"gram_trace_{_k}", f"{_with(_m)} SELECT CAST(0 AS BIGINT) AS rid, CAST(0 AS BIGINT) AS cid, {_val('sum(val * val)', _r)} AS val FROM {_k}", _r)(lambda s, d, m=_m: gram(MATRICES[m](s, d)).trace())

for _m, _i, _j in (("QPS", 1, 1), ("QCP", 1, 1), ("EMB", 1, 1), ("QPS", 1, 2)):
    _r, _k = _m == "EMB", _m.lower()
    query(
        f"gram_entry_{_k}" if _i == _j else "gram_entry_ij",
        f"{_with(_m)} SELECT x.cid AS rid, y.cid AS cid, {_val('sum(x.val * y.val)', _r)} AS val FROM {_k} x JOIN {_k} y ON x.rid = y.rid WHERE x.cid = {_i} AND y.cid = {_j} GROUP BY 1, 2",
        _r,
    )(lambda s, d, m=_m, i=_i, j=_j: gram(MATRICES[m](s, d)).entry(i, j))

query("gram_trace_qps_noopt", ORACLES["gram_trace_qps"])(lambda s, d: gram(_qps(s, d)).trace().using(Engine(rules=frozenset())))
query("gram_rowsum_qps_noopt", ORACLES["gram_rowsum_qps"])(lambda s, d: gram(_qps(s, d)).row_sums().using(Engine(rules=frozenset())))

# Least squares


def _design(df: DataFrame, row: str, columns: list[Column]) -> DataFrame:
    return from_features(df, row, columns)


def _numbered(df: DataFrame) -> DataFrame:
    """Row ids for a table without a key: the order of rows does not matter to a regression."""
    return df.withColumn("__r", F.monotonically_increasing_id())


def _row_of(b: Matrix, i: int) -> DataFrame:
    return b.cells().select("rid", "cid", F.round("val", 6).alias("val"))


def _lineitem_xy(s, d):
    from gridalg.functions.lineage import cut

    li = cut(_numbered(table(s, d, "lineitem").select("l_quantity", "l_extendedprice")))
    m = 1 << 62
    x = Matrix.of(_design(li, "__r", [F.lit(1.0), F.col("l_quantity")]), m, 2)
    y = Matrix.of(_design(li, "__r", [F.col("l_extendedprice")]), m, 1)
    return x, y


query(
    "linreg_row_lineitem",
    "SELECT CAST(1 AS BIGINT) AS rid, CAST(0 AS BIGINT) AS cid, round(regr_slope(l_extendedprice, l_quantity), 6) AS val FROM lineitem",
)(lambda s, d: _row_of(linreg_row(*_lineitem_xy(s, d), 1), 1))


def _part_xy(s, d):
    x = from_features(table(s, d, "part"), "p_partkey", [F.lit(1.0), F.col("p_size"), F.col("p_retailprice")])
    y = from_table(table(s, d, "lineitem").select("l_partkey", "l_quantity"), "l_partkey", "0", "l_quantity")
    n = _rows(s, d, "part")
    return Matrix.of(x, n, 3), Matrix.of(y, n, 1)


query(
    "linreg_row_part",
    """WITH d AS (SELECT CAST(p_size AS DOUBLE) AS u, p_retailprice AS v, coalesce(y, 0) AS y FROM part LEFT JOIN (SELECT l_partkey, sum(l_quantity) AS y FROM lineitem GROUP BY 1) ON p_partkey = l_partkey),
    c AS (SELECT u - avg(u) OVER () AS u, v - avg(v) OVER () AS v, y - avg(y) OVER () AS y FROM d),
    s AS (SELECT sum(u * u) AS uu, sum(v * v) AS vv, sum(u * v) AS uv, sum(u * y) AS uy, sum(v * y) AS vy FROM c)
    SELECT CAST(1 AS BIGINT) AS rid, CAST(0 AS BIGINT) AS cid, round((uy * vv - vy * uv) / (uu * vv - uv * uv), 6) AS val FROM s""",
)(lambda s, d: _row_of(linreg_row(*_part_xy(s, d), 1), 1))


def _label_xy(s, d):
    both = table(s, d, "documents").select("doc_id", "n_chars").join(table(s, d, "labels"), "doc_id").filter("quality IS NOT NULL")
    n = _rows(s, d, "documents")
    return Matrix.of(from_features(both, "doc_id", [F.lit(1.0), F.col("n_chars") / 1000]), n, 2), Matrix.of(from_features(both, "doc_id", [F.col("quality")]), n, 1)


query(
    "linreg_row_labels",
    "SELECT CAST(1 AS BIGINT) AS rid, CAST(0 AS BIGINT) AS cid, round(regr_slope(quality, n_chars / 1000.0), 6) AS val FROM documents JOIN labels USING (doc_id)",
)(lambda s, d: _row_of(linreg_row(*_label_xy(s, d), 1), 1))

# Kronecker products

for _n, _a, _b in (("sd", "SXN", "TNN"), ("ss", "SXN", "RXN"), ("ds", "TNN", "SXN"), ("dd", "TNN", "TNN")):
    _p = {"TNN": "25", "RXN": "5", "SXN": "(SELECT count(*) FROM supplier)"}[_b]
    query(f"kron_{_n}", f"{_with(_a, _b)} SELECT x.rid * {_p} + y.rid AS rid, x.cid * 25 + y.cid AS cid, x.val * y.val AS val FROM {_a.lower()} x CROSS JOIN {_b.lower()} y")(lambda s, d, a=_a, b=_b: MATRICES[a](s, d).kron(MATRICES[b](s, d)))

# overlays

_F = {"add": (ADD, "x + y"), "mul": (MUL, "x * y"), "lefty": (LEFTY, "x * (y + 1)"), "max": (MAX, "greatest(x, y)")}


def _pad(m: Matrix, shape: tuple[int, int]) -> Matrix:
    return Matrix.of(m.cells(), *shape)


def _grow(a: Matrix, b: Matrix) -> tuple[Matrix, Matrix]:
    shape = max(a.shape[0], b.shape[0]), max(a.shape[1], b.shape[1])
    return _pad(a, shape), _pad(b, shape)


def _overlay_sql(a: str, b: str, how: str, expr: str, turned: bool = False) -> str:
    on = "p.rid = q.cid AND p.cid = q.rid" if turned else "p.rid = q.rid AND p.cid = q.cid"
    q = ("q.cid", "q.rid") if turned else ("q.rid", "q.cid")
    return f"{_with(a, b)}, j AS (SELECT coalesce(p.rid, {q[0]}) AS rid, coalesce(p.cid, {q[1]}) AS cid, coalesce(p.val, 0) AS x, coalesce(q.val, 0) AS y FROM {a.lower()} p {how} JOIN {b.lower()} q ON {on}) SELECT rid, cid, {expr} AS val FROM j"


for _n, (_f, _e) in _F.items():
    _how = {"mul": "INNER", "lefty": "LEFT"}.get(_n, "FULL")
    query(f"overlay_direct_{_n}", _overlay_sql("CUE", "CUH", _how, _e))(lambda s, d, f=_f: _grow(_cue(s, d), _cuh(s, d))[0].join(_grow(_cue(s, d), _cuh(s, d))[1], "overlay", f))
query("overlay_direct_qol_cue", _overlay_sql("QOL", "CUE", "FULL", "x + y"))(lambda s, d: _grow(_qol(s, d), _cue(s, d))[0].join(_grow(_qol(s, d), _cue(s, d))[1], "overlay", ADD))
for _n in ("add", "mul"):
    _f, _e = _F[_n]
    query(f"overlay_transpose_{_n}", _overlay_sql("TNN", "TNN", "FULL" if _n == "add" else "INNER", _e, True))(lambda s, d, f=_f: _tnn(s, d).join(_tnn(s, d), "RID=CID AND CID=RID", f))


def _cost(s, d):
    li = table(s, d, "lineitem").select("l_suppkey", "l_partkey", "l_linenumber")
    return Matrix.of(from_table(li, "l_suppkey", "l_partkey", "l_linenumber"), _rows(s, d, "supplier"), _rows(s, d, "part"), name="COST", at_most=_rows(s, d, "lineitem"))


SQL["COST"] = "SELECT l_suppkey AS rid, l_partkey AS cid, CAST(sum(l_linenumber) AS DOUBLE) AS val FROM lineitem GROUP BY 1, 2"
query("overlay_transpose_cost", _overlay_sql("QPS", "COST", "INNER", "x * y", True))(lambda s, d: _qps(s, d).join(_cost(s, d), "transpose", MUL))
query("overlay_direct_add1", f"{_with('TNN')}, g AS (SELECT i AS rid, j AS cid FROM range(25) a(i), range(25) b(j)) SELECT rid, cid, 2 * coalesce(val, 0) + 1 AS val FROM g LEFT JOIN tnn USING (rid, cid)")(lambda s, d: _tnn(s, d).join(_tnn(s, d), "overlay", ADD1))

# Joins on one dimension


def _d2d_sql(a: str, b: str, p: str, q: str) -> str:
    o = {"rid": "cid", "cid": "rid"}
    return f"{_with(a, b)} SELECT x.{p} AS d1, x.{o[p]} AS d2, y.{o[q]} AS d3, x.val * y.val AS val FROM {a.lower()} x JOIN {b.lower()} y ON x.{p} = y.{q} WHERE x.val <> 0 AND y.val <> 0"


for _n, _a, _b, _p, _q in (
    ("rr_sd", "CUE", "TNN", "rid", "rid"),
    ("rr_ds", "TNN", "CUE", "rid", "rid"),
    ("rr_dd", "TNN", "TNN", "rid", "rid"),
    ("rc", "CUE", "TNN", "rid", "cid"),
    ("cc", "CUE", "RXN", "cid", "cid"),
):
    query(f"d2d_{_n}", _d2d_sql(_a, _b, _p, _q))(lambda s, d, a=_a, b=_b, p=_p, q=_q: MATRICES[a](s, d).join(MATRICES[b](s, d), f"{p}={q}", MUL))


query("d2d_cr", f"WITH t AS ({_d2d_sql('QPS', 'TNN', 'cid', 'rid')}) SELECT count(*) AS n, sum(val) AS total FROM t")(lambda s, d: _qps(s, d).join(_tnn(s, d), "CID=RID", MUL).cells.agg(F.count("*").alias("n"), F.sum("val").alias("total")))
query("d2d_rr_ss", f"WITH t AS ({_d2d_sql('QPS', 'QPS', 'rid', 'rid')}) SELECT count(*) AS n, sum(val) AS total FROM t")(lambda s, d: _qps(s, d).join(_qps(s, d), "RID=RID", MUL).totals())
query("d2d_lefty", f"{_with('CUE', 'TNN')}, g AS (SELECT x.rid AS d1, x.cid AS d2, j AS d3, x.val AS x FROM cue x, range(25) b(j) WHERE x.rid < 25) SELECT d1, d2, d3, x * (coalesce(y.val, 0) + 1) AS val FROM g LEFT JOIN tnn y ON y.rid = d1 AND y.cid = d3")(lambda s, d: _cue(s, d).join(_tnn(s, d), "rid=rid", LEFTY))

# Joins on values


def _v2v_sql(a: str, b: str) -> str:
    return f"{_with(a, b)} SELECT x.rid AS d1, x.cid AS d2, y.rid AS d3, y.cid AS d4, x.val * y.val AS val FROM {a.lower()} x JOIN {b.lower()} y ON x.val = y.val WHERE x.val <> 0"


for _n, _a, _b, _s in (("v2v_hit", "CUE", "CUH", "auto"), ("v2v_miss", "TNN", "QCP", "auto"), ("v2v_bloom", "CUE", "CUH", "bloom"), ("v2v_sparse", "CUE", "CUH", "sparse"), ("v2v_bloom_sparse", "CUE", "CUH", "bloom_sparse"), ("v2v_nested_loop", "CUE", "CUH", "nested_loop")):
    query(_n, _v2v_sql(_a, _b))(lambda s, d, a=_a, b=_b, st=_s: MATRICES[a](s, d).join(MATRICES[b](s, d), "VAL=VAL", MUL, strategy=st))
query(
    "v2v_emb_summary",
    f"{_with('EMB')}, e AS (SELECT round(val, 3) + 0.0 AS val FROM emb) SELECT count(*) AS n FROM e x JOIN e y ON x.val = y.val WHERE x.val <> 0",
)(lambda s, d: (lambda m: m.join(m, "val=val", MUL).cells.agg(F.count("*").alias("n")))(_emb(s, d).map(lambda x: F.round(x, 3) + 0.0, "round", True)))
query("v2v_block_bloom", f"{_with('CUE', 'CUH')} SELECT x.rid AS ar, x.cid AS ac, y.rid AS br, y.cid AS bc, x.val FROM cue x JOIN cuh y ON x.val = y.val WHERE x.val <> 0")(lambda s, d: block_join(_cue(s, d).cells(), _cuh(s, d).cells(), 50))

# Joins of a dimension with values


def _dv_sql(a: str, b: str, p: str, q: str) -> str:
    return f"{_with(a, b)} SELECT x.rid AS d1, x.cid AS d2, y.rid AS d3, y.cid AS d4, x.val * y.val AS val FROM {a.lower()} x JOIN {b.lower()} y ON x.{p} = y.{q} WHERE x.val <> 0 AND y.val <> 0"


for _n, _a, _b, _p, _q in (("d2v_rid", "TNN", "CUE", "rid", "val"), ("d2v_cid", "TNN", "CUE", "cid", "val"), ("v2d_rid", "CSN", "TNN", "val", "rid"), ("v2d_cid", "CSN", "TNN", "val", "cid")):
    query(_n, _dv_sql(_a, _b, _p, _q))(lambda s, d, a=_a, b=_b, p=_p, q=_q: MATRICES[a](s, d).join(MATRICES[b](s, d), f"{p}={q}", MUL))
    query(f"{_n}_bloom", ORACLES[_n])(lambda s, d, a=_a, b=_b, p=_p, q=_q: MATRICES[a](s, d).join(MATRICES[b](s, d), f"{p}={q}", MUL, strategy="bloom"))
query("d2d_bloom", ORACLES["d2d_rr_sd"])(lambda s, d: _cue(s, d).join(_tnn(s, d), "rid=rid", MUL, strategy="bloom"))


def _choices(s, d) -> DataFrame:
    """What the cost model chooses for each workload join of these tables: strategy, moved entries and placement."""
    pairs = [("rid=rid", "QPS", "QPS"), ("cid=rid", "QPS", "TNN"), ("rid=rid", "CUE", "TNN"), ("val=val", "CUE", "CUH"), ("val=val", "TNN", "QCP"), ("rid=val", "TNN", "CUE"), ("val=rid", "CSN", "TNN"), ("overlay", "CUE", "CUH"), ("cross", "SXN", "TNN")]
    rows = []
    for g, a, b in pairs:
        c = MATRICES[a](s, d).choose(MATRICES[b](s, d), g, MUL)
        rows.append((f"{a} {b} {g}", c.strategy, c.sizes[0], c.sizes[1], c.placement.sa.value, c.placement.sb.value, float(c.placement.cost)))
    return s.createDataFrame(rows, "join string, strategy string, a long, b long, sa string, sb string, moved double")


query("join_choices", None)(_choices)

# Factorisation, one iteration from fixed start values

_RANK = 4


def _pnmf_sql() -> str:
    return f"""{_with('QCP')}, k AS (SELECT j FROM range({_RANK}) t(j)),
    w0 AS (SELECT i, j, ((i * 7 + j * 3) % 11 + 1) / 11.0::DOUBLE AS v FROM range((SELECT count(*) FROM customer)) r(i), k),
    h0 AS (SELECT i, j, ((i * 3 + j * 7) % 11 + 1) / 11.0::DOUBLE AS v FROM range((SELECT count(*) FROM part)) r(i), k),
    s0 AS (SELECT q.rid, q.cid, any_value(q.val) AS val, sum(w0.v * h0.v) AS s FROM qcp q JOIN w0 ON w0.i = q.rid JOIN h0 ON h0.i = q.cid AND h0.j = w0.j WHERE q.val <> 0 GROUP BY 1, 2),
    hs AS (SELECT j, sum(v) AS t FROM h0 GROUP BY j),
    wn AS (SELECT s0.rid AS i, h0.j, sum(s0.val / s0.s * h0.v) AS n FROM s0 JOIN h0 ON h0.i = s0.cid GROUP BY 1, 2),
    w1 AS (SELECT w0.i, w0.j, w0.v * coalesce(wn.n, 0) / hs.t AS v FROM w0 JOIN hs USING (j) LEFT JOIN wn ON wn.i = w0.i AND wn.j = w0.j),
    s1 AS (SELECT s0.rid, s0.cid, any_value(s0.val) AS val, sum(w1.v * h0.v) AS s FROM s0 JOIN w1 ON w1.i = s0.rid JOIN h0 ON h0.i = s0.cid AND h0.j = w1.j GROUP BY 1, 2),
    ws AS (SELECT j, sum(v) AS t FROM w1 GROUP BY j),
    hn AS (SELECT s1.cid AS i, w1.j, sum(s1.val / s1.s * w1.v) AS n FROM s1 JOIN w1 ON w1.i = s1.rid GROUP BY 1, 2),
    h1 AS (SELECT h0.i, h0.j, h0.v * coalesce(hn.n, 0) / ws.t AS v FROM h0 JOIN ws USING (j) LEFT JOIN hn ON hn.i = h0.i AND hn.j = h0.j),
    s2 AS (SELECT s0.rid, s0.cid, any_value(s0.val) AS val, sum(w1.v * h1.v) AS s FROM s0 JOIN w1 ON w1.i = s0.rid JOIN h1 ON h1.i = s0.cid AND h1.j = w1.j GROUP BY 1, 2)"""


def _flat(rows: DataFrame) -> DataFrame:
    return rows.select(F.col("id").alias("rid"), F.posexplode("vec").alias("p", "val")).select("rid", F.col("p").cast("long").alias("cid"), "val")


query("pnmf_iter1_w", f"{_pnmf_sql()} SELECT i AS rid, j AS cid, round(v, 6) + 0.0 AS val FROM w1", True)(lambda s, d: _flat((lambda a: nmf.step(a, nmf.start(a, _RANK), nmf.prepare(a, _RANK)).w)(_qcp(s, d))))
query("pnmf_iter1_h", f"{_pnmf_sql()} SELECT i AS rid, j AS cid, round(v, 6) + 0.0 AS val FROM h1", True)(lambda s, d: _flat((lambda a: nmf.step(a, nmf.start(a, _RANK), nmf.prepare(a, _RANK)).h)(_qcp(s, d))))


def _objective(steps: int):
    def run(s, d):
        a = _qcp(s, d)
        f = nmf.start(a, _RANK)
        for _ in range(steps):
            f = nmf.step(a, f)  # vectors brought to nonzeros; pnmf_iter1 takes the grid
        return nmf.objective(a, f).select(F.round("objective", 3).alias("objective"))

    return run


_OBJ = "SELECT round((SELECT sum(a.t * b.t) FROM (SELECT j, sum(v) AS t FROM {w} GROUP BY j) a JOIN (SELECT j, sum(v) AS t FROM {h} GROUP BY j) b USING (j)) - (SELECT sum(val * ln(s)) FROM {s}), 3) AS objective"
query("pnmf_objective_0", f"{_pnmf_sql()} {_OBJ.format(w='w0', h='h0', s='s0')}")(_objective(0))
query("pnmf_objective_1", f"{_pnmf_sql()} {_OBJ.format(w='w1', h='h1', s='s2')}")(_objective(1))

# recommendation
query("recommend_topk", None)(lambda s, d: nmf.recommend(_qcp(s, d).T, _pfx(s, d), 4, 5).withColumn("val", F.round("val", 6)))

# Pushdown of the opening example, tensors, chains
query(
    "rowsum_product_of_sum",
    f"{_with('RXN', 'TNN')} SELECT r.rid, CAST(0 AS BIGINT) AS cid, sum(r.val * t.val) AS val FROM rxn r JOIN (SELECT rid, cid, val FROM tnn UNION ALL SELECT cid, rid, val FROM tnn) t ON r.cid = t.rid GROUP BY r.rid",
)(lambda s, d: (_rxn(s, d) @ (_tnn(s, d) + _tnn(s, d).T)).row_sums())
query("tensor_agg_d2", f"WITH t AS ({_d2d_sql('QPS', 'QPS', 'rid', 'rid')}) SELECT d1, d3, sum(val) AS val FROM t GROUP BY 1, 2")(lambda s, d: _qps(s, d).join(_qps(s, d), "rid=rid", MUL).agg("sum", ("d2",)))
query("tensor_agg_d3", f"WITH t AS ({_d2d_sql('QPS', 'QPS', 'rid', 'rid')}) SELECT d1, d2, sum(val) AS val FROM t GROUP BY 1, 2")(lambda s, d: _qps(s, d).join(_qps(s, d), "rid=rid", MUL).agg("sum", ("d3",)))
query("tensor_agg_d1", f"WITH t AS ({_d2d_sql('QPS', 'QPS', 'rid', 'rid')}) SELECT d2, d3, sum(val) AS val FROM t GROUP BY 1, 2")(lambda s, d: _qps(s, d).join(_qps(s, d), "rid=rid", MUL).agg("sum", ("d1",)))
query("tensor_max_d2", f"WITH t AS ({_d2d_sql('QPS', 'TNN', 'cid', 'rid')}) SELECT d1, d3, max(val) AS val FROM t GROUP BY 1, 2")(lambda s, d: _qps(s, d).join(_tnn(s, d), "cid=rid", MUL).agg("max", ("d2",)))
query("tensor_max_d1", f"WITH t AS ({_d2d_sql('CUE', 'TNN', 'rid', 'rid')}) SELECT d2, d3, max(val) AS val FROM t GROUP BY 1, 2")(lambda s, d: _cue(s, d).join(_tnn(s, d), "rid=rid", MUL).laid_out(("d1",)).agg("max", ("d1",)))
query("tensor_select", f"WITH t AS ({_d2d_sql('QPS', 'TNN', 'cid', 'rid')}) SELECT d1, d2, d3, val FROM t WHERE d1 BETWEEN 2 AND 9 AND d2 < 100 AND d3 = 4")(lambda s, d: _qps(s, d).join(_tnn(s, d), "cid=rid", MUL).select(d1=(2, 9), d2=(0, 99), d3=4))
query("chain_region_trade", f"{_with('RXN', 'TNN')} SELECT a.rid, b.rid AS cid, sum(t.val) AS val FROM rxn a JOIN tnn t ON a.cid = t.rid JOIN rxn b ON b.cid = t.cid GROUP BY 1, 2")(lambda s, d: _rxn(s, d) @ _tnn(s, d) @ _rxn(s, d).T)
query("tensor_of_predictions", f"{_with('RXN', 'TNN')}, p AS (SELECT a.rid, t.cid, sum(t.val) AS val FROM rxn a JOIN tnn t ON a.cid = t.rid GROUP BY 1, 2) SELECT p.cid AS d1, p.rid AS d2, t.cid AS d3, p.val * t.val AS val FROM p JOIN tnn t ON p.cid = t.rid")(lambda s, d: (_rxn(s, d) @ _tnn(s, d)).join(_tnn(s, d), "CID=RID", MUL))

# aggregates
query("avg_rating_by_user", f"{_with('QCP')} SELECT rid, CAST(0 AS BIGINT) AS cid, round(sum(val) / count(*) FILTER (val <> 0), 6) + 0.0 AS val FROM qcp GROUP BY rid", True)(lambda s, d: _qcp(s, d).agg("avg", "r"))


def _agg_sql(m: str, fn: str, dim: str, rounded: bool) -> str:
    t, n, k = m.lower(), NROWS[m], NCOLS[m]
    length = {"r": k, "c": n, "d": n, "a": f"({n} * {k})"}[dim]
    value = {
        "sum": "sum(val)",
        "nnz": "CAST(count(*) FILTER (val <> 0) AS DOUBLE)",
        "avg": "sum(val) / nullif(count(*) FILTER (val <> 0), 0)",
        "max": f"CASE WHEN count(*) < {length} THEN greatest(max(val), 0) ELSE max(val) END",
        "min": f"CASE WHEN count(*) < {length} THEN least(min(val), 0) ELSE min(val) END",
    }[fn]
    key = {"r": "rid, CAST(0 AS BIGINT) AS cid", "c": "CAST(0 AS BIGINT) AS rid, cid"}.get(dim, "CAST(0 AS BIGINT) AS rid, CAST(0 AS BIGINT) AS cid")
    group = {"r": "GROUP BY rid", "c": "GROUP BY cid"}.get(dim, "")
    return f"{_with(m)} SELECT {key}, {_val(value, rounded)} AS val FROM {t} {'WHERE rid = cid' if dim == 'd' else ''} {group}"


for _fn in ("sum", "nnz", "avg", "max", "min"):
    for _d in "rcda":
        _r = _fn == "avg"
        query(f"agg_{_fn}_{_d}", _agg_sql("TNN", _fn, _d, _r), _r)(lambda s, d, f=_fn, k=_d: _tnn(s, d).agg(f, k))
    query(f"agg_{_fn}_r_qol", _agg_sql("QOL", _fn, "r", _fn == "avg"), _fn == "avg")(lambda s, d, f=_fn: _qol(s, d).agg(f, "r"))
    query(f"agg_{_fn}_c_emb", _agg_sql("EMB", _fn, "c", True), True)(lambda s, d, f=_fn: _emb(s, d).agg(f, "c"))

# selections
_SELECTS: dict[str, tuple[str, Callable[[Matrix], Matrix], str]] = {
    "value": ("QPS", lambda m: m.select(VAL == 10), "val = 10"),
    "cascade": ("QPS", lambda m: m.select(VAL > 20).select(RID < 100).select(CID >= 10), "val > 20 AND rid < 100 AND cid >= 10"),
    "row": ("QPS", lambda m: m.row(5), "rid = 5"),
    "col": ("QPS", lambda m: m.col(3), "cid = 3"),
    "rows": ("QOL", lambda m: m.rows(10, 200), "rid BETWEEN 10 AND 200"),
    "cols": ("QOL", lambda m: m.cols(1, 3), "cid BETWEEN 1 AND 3"),
    "mixed": ("QPS", lambda m: m.select((VAL > 30) & (RID == 5)), "val > 30 AND rid = 5"),
    "or_not": ("QOL", lambda m: m.select((VAL > 90) | ~(VAL >= 2)).select(VAL > 0), "(val > 90 OR val < 2) AND val > 0"),
    "diag": ("TNN", lambda m: m.diag(), "rid = cid"),
    "entry": ("QPS", lambda m: m.entry(1, 1), "rid = 1 AND cid = 1"),
    "val_over_dim": ("QOL", lambda m: m.select((VAL > RID) & (VAL > 0)), "val > rid AND val > 0"),
    "under_transpose": ("QPS", lambda m: m.T.select((RID == 3) & (CID < 50)).T, "cid = 3 AND rid < 50"),
}
for _n, (_m, _f, _w) in _SELECTS.items():
    query(f"select_{_n}", f"{_with(_m)} SELECT rid, cid, val FROM {_m.lower()} WHERE {_w}")(lambda s, d, m=_m, f=_f: f(MATRICES[m](s, d)))
query("select_nonempty_rows", f"{_with('QOL')} SELECT rid, cid, val FROM qol WHERE rid IN (SELECT rid FROM qol)")(lambda s, d: _qol(s, d).select_nonempty_rows())
query("select_nonempty_cols", f"{_with('CTL')} SELECT rid, cid, val FROM ctl")(lambda s, d: _ctl(s, d).select_nonempty_cols())
query("select_reindexed_rows", f"{_with('QOL')}, k AS (SELECT rid, row_number() OVER (ORDER BY rid) - 1 AS n FROM (SELECT DISTINCT rid FROM qol)) SELECT k.n AS rid, cid, val FROM qol JOIN k USING (rid)")(lambda s, d: _qol(s, d).select_nonempty_rows().reindex())
query("top3_per_row", f"{_with('QOL')}, r AS (SELECT *, row_number() OVER (PARTITION BY rid ORDER BY val DESC, cid) AS rank FROM qol) SELECT rid, CAST(rank AS INTEGER) AS rank, cid, val FROM r WHERE rank <= 3")(lambda s, d: _qol(s, d).top(3))

# Each rule on against off gives the same; here the rewritten plans against SQL
_N = "25"
query("rule_sum_scalar_add_r", f"{_with('TNN')} SELECT i AS rid, CAST(0 AS BIGINT) AS cid, coalesce(sum(val), 0) + 2.5 * 25 AS val FROM range(25) r(i) LEFT JOIN tnn ON rid = i GROUP BY i")(lambda s, d: (_tnn(s, d) + 2.5).row_sums())
query("rule_trace_scalar_add", f"{_with('TNN')} SELECT CAST(0 AS BIGINT) AS rid, CAST(0 AS BIGINT) AS cid, sum(val) + 2.5 * 25 AS val FROM tnn WHERE rid = cid")(lambda s, d: (_tnn(s, d) + 2.5).trace())
query("rule_sum_scalar_mul_c", f"{_with('TNN')} SELECT CAST(0 AS BIGINT) AS rid, cid, sum(val) * -2 AS val FROM tnn GROUP BY cid")(lambda s, d: (_tnn(s, d) * -2).col_sums())
query("rule_min_negative_scale", f"{_with('EMB')} SELECT CAST(0 AS BIGINT) AS rid, cid, round(-2 * max(val), 6) + 0.0 AS val FROM emb GROUP BY cid", True)(lambda s, d: (_emb(s, d) * -2).agg("min", "c"))
query("rule_total_of_product", f"{_with('QPS')}, g AS (SELECT x.cid, y.cid AS c2, sum(x.val * y.val) AS val FROM qps x JOIN qps y ON x.rid = y.rid GROUP BY 1, 2) SELECT CAST(0 AS BIGINT) AS rid, CAST(0 AS BIGINT) AS cid, sum(val) AS val FROM g")(lambda s, d: gram(_qps(s, d)).total())
query("rule_sum_of_sum", f"{_with('TNN')} SELECT rid, CAST(0 AS BIGINT) AS cid, sum(val) AS val FROM (SELECT rid, val FROM tnn UNION ALL SELECT cid, val FROM tnn) GROUP BY rid")(lambda s, d: (_tnn(s, d) + _tnn(s, d).T).row_sums())
query("rule_select_row_of_product", f"{_with('RXN', 'TNN')} SELECT r.rid, t.cid, sum(t.val) AS val FROM rxn r JOIN tnn t ON r.cid = t.rid WHERE r.rid = 2 GROUP BY 1, 2")(lambda s, d: (_rxn(s, d) @ _tnn(s, d)).row(2))
query("rule_avg_of_transpose", f"{_with('QOL')} SELECT rid, CAST(0 AS BIGINT) AS cid, round(sum(val) / count(*) FILTER (val <> 0), 6) + 0.0 AS val FROM qol GROUP BY rid", True)(lambda s, d: _qol(s, d).T.agg("avg", "c").T)
query("rule_ones", f"{_with('QOL')} SELECT rid, CAST(0 AS BIGINT) AS cid, sum(val) AS val FROM qol GROUP BY rid")(lambda s, d: _qol(s, d) @ Matrix.ones(s, 7, 1))

# elementwise operators, inverse and QR
query("elem_add", f"{_with('TNN')} SELECT rid, cid, sum(val) AS val FROM (SELECT rid, cid, val FROM tnn UNION ALL SELECT cid, rid, val FROM tnn) GROUP BY 1, 2")(lambda s, d: _tnn(s, d) + _tnn(s, d).T)
query("elem_mul", f"{_with('TNN')} SELECT a.rid, a.cid, a.val * b.val AS val FROM tnn a JOIN tnn b ON a.rid = b.cid AND a.cid = b.rid")(lambda s, d: _tnn(s, d) * _tnn(s, d).T)
query("elem_div", f"{_with('TNN')} SELECT a.rid, a.cid, round(CASE WHEN a.val = 0 THEN 0 WHEN b.val <> 0 THEN a.val / b.val END, 6) + 0.0 AS val FROM tnn a LEFT JOIN tnn b ON a.rid = b.cid AND a.cid = b.rid", True)(lambda s, d: _tnn(s, d) / _tnn(s, d).T)
query("map_log", f"{_with('QOL')} SELECT rid, cid, round(ln(val), 6) + 0.0 AS val FROM qol", True)(lambda s, d: _qol(s, d).log())
query("product_tiles", f"{_with('RXN', 'TNN')} SELECT r.rid, t.cid, sum(r.val * t.val) AS val FROM rxn r JOIN tnn t ON r.cid = t.rid GROUP BY 1, 2")(lambda s, d: tiles.to_cells(tiles.multiply(tiles.to_tiles(_rxn(s, d).cells(), 5, 25, 10), tiles.to_tiles(_tnn(s, d).cells(), 25, 25, 10)), 10))
query("tiles_round_trip", f"{_with('QPS')} SELECT rid, cid, val FROM qps WHERE val <> 0")(lambda s, d: (lambda m: tiles.to_cells(tiles.to_tiles(m.cells(), *m.shape, 64), 64))(_qps(s, d)))
# all columns but one brand, which the others and the ones give; over 997, so that neither the order of additions nor ties show
query("qr_r_squared", f"{_with('PFX')}, x AS (SELECT rid, CASE WHEN cid > 3 THEN cid - 1 ELSE cid END AS cid, val FROM pfx WHERE cid <> 3) SELECT x.cid AS rid, y.cid, round(sum(x.val * y.val) / 997, 3) AS val FROM x JOIN x y ON x.rid = y.rid GROUP BY 1, 2 HAVING round(sum(x.val * y.val) / 997, 3) <> 0")(lambda s, d: _r_squared(_pfx(s, d)))


def _r_squared(m: Matrix) -> DataFrame:
    cells = m.cells().filter("cid <> 3").withColumn("cid", F.when(F.col("cid") > 3, F.col("cid") - 1).otherwise(F.col("cid")))
    r = qr(Matrix.of(cells, m.shape[0], m.shape[1] - 1))[1]
    return (r.T @ r).cells().select("rid", "cid", F.round(F.col("val") / 997, 3).alias("val")).filter("val <> 0")

query("product_shuffle_inner", f"{_with('RXN', 'TNN')} SELECT r.rid, t.cid, sum(r.val * t.val) AS val FROM rxn r JOIN tnn t ON r.cid = t.rid GROUP BY 1, 2")(lambda s, d: _rxn(s, d).matmul(_tnn(s, d), "shuffle_inner"))
query("product_row_stationary", ORACLES["product_shuffle_inner"])(lambda s, d: _rxn(s, d).matmul(_tnn(s, d), "row_stationary"))
query("avg_dense_qol", f"{_with('QOL')} SELECT rid, CAST(0 AS BIGINT) AS cid, round(sum(val) / 7, 6) + 0.0 AS val FROM qol GROUP BY rid", True)(lambda s, d: _qol(s, d).avg_dense("r"))
query("argmax_qol", f"{_with('QOL')}, r AS (SELECT *, row_number() OVER (PARTITION BY rid ORDER BY val DESC, cid) AS k FROM qol) SELECT rid, cid, val FROM r WHERE k = 1")(lambda s, d: _qol(s, d).argmax())
query("outliers_ctl", f"{_with('CTL')}, l AS (SELECT rid, avg(val) AS m, stddev_pop(val) AS sd FROM ctl GROUP BY rid) SELECT rid, cid, val, round((val - m) / sd, 6) AS z FROM ctl JOIN l USING (rid) WHERE sd > 0 AND abs((val - m) / sd) > 2")(lambda s, d: _ctl(s, d).outliers(2.0).withColumn("z", F.round("z", 6)))

# Zipf-skewed tokens: documents and benchmark items over one dictionary
_TOK = "WITH d AS (SELECT doc_id AS rid, w, CAST(count(*) AS DOUBLE) AS val FROM (SELECT doc_id, unnest(string_split(text, ' ')) AS w FROM documents) GROUP BY 1, 2), b AS (SELECT item_id AS rid, w, CAST(count(*) AS DOUBLE) AS val FROM (SELECT item_id, unnest(string_split(text, ' ')) AS w FROM benchmark) GROUP BY 1, 2)"


def _tokens(s, d) -> tuple[Matrix, Matrix]:
    docs = table(s, d, "documents").select(F.col("doc_id").alias("r"), F.explode(F.split("text", " ")).alias("w"))
    items = table(s, d, "benchmark").select(F.col("item_id").alias("r"), F.explode(F.split("text", " ")).alias("w"))
    codes, n = dense_codes(docs.select("w").unionByName(items.select("w")))
    return tuple(Matrix.of(from_table(t.join(codes, "w"), "r", "code"), m, n) for t, m in ((docs, _rows(s, d, "documents")), (items, _rows(s, d, "benchmark"))))


query("token_overlap_salted", f"{_TOK} SELECT d.rid, b.rid AS cid, sum(d.val * b.val) AS val FROM d JOIN b USING (w) GROUP BY 1, 2")(lambda s, d: (lambda t: t[0].matmul(t[1].T, "salted", heavy=200))(_tokens(s, d)))
query("d2d_tokens_salted", f"{_TOK} SELECT count(*) AS n, sum(d.val * b.val) AS total FROM d JOIN b USING (w)")(lambda s, d: (lambda t: join_salted(Operand(t[0].cells(), *t[0].shape), Operand(t[1].cells(), *t[1].shape), "cid=cid", MUL, heavy=200).agg(F.count("*").alias("n"), F.sum("val").alias("total")))(_tokens(s, d)))

# folds
query("kfold_test", f"{_with('QCP')} SELECT rid % 5 AS fold, count(*) AS n, sum(val) AS total FROM qcp GROUP BY 1")(lambda s, d: _folds(s, d, 1))
query("kfold_train", f"{_with('QCP')} SELECT f AS fold, count(*) AS n, sum(val) AS total FROM qcp, range(5) r(f) WHERE rid % 5 <> f GROUP BY 1")(lambda s, d: _folds(s, d, 0))


def _folds(s, d, part: int) -> DataFrame:
    out = None
    for i, pair in enumerate(_qcp(s, d).kfold(5)):
        one = pair[part].cells().agg(F.count("*").alias("n"), F.sum("val").alias("total")).select(F.lit(i).cast("long").alias("fold"), "n", "total")
        out = one if out is None else out.unionByName(one)
    return out


query(
    "cross_validate_part",
    """WITH d AS (SELECT p_partkey AS r, CAST(p_size AS DOUBLE) AS u, p_retailprice AS v, y FROM part LEFT JOIN (SELECT l_partkey, sum(l_quantity) AS y FROM lineitem GROUP BY 1) ON p_partkey = l_partkey),
    t AS (SELECT f, u, v, coalesce(y, 0) AS y FROM d, range(3) k(f) WHERE r % 3 <> f),
    m AS (SELECT f, avg(u) AS mu, avg(v) AS mv, avg(y) AS my FROM t GROUP BY f),
    s AS (SELECT f, sum((u - mu) ** 2) AS uu, sum((v - mv) ** 2) AS vv, sum((u - mu) * (v - mv)) AS uv, sum((u - mu) * (y - my)) AS uy, sum((v - mv) * (y - my)) AS vy FROM t JOIN m USING (f) GROUP BY f),
    b AS (SELECT f, (uy * vv - vy * uv) / (uu * vv - uv * uv) AS bu, (vy * uu - uy * uv) / (uu * vv - uv * uv) AS bv FROM s)
    SELECT CAST(f AS INTEGER) AS fold, count(*) AS n, round(sum((y - (my + bu * (u - mu) + bv * (v - mv))) ** 2) / 1000, 3) AS sse
    FROM d JOIN b ON r % 3 = f JOIN m USING (f) WHERE y IS NOT NULL GROUP BY f""",
)(lambda s, d: cross_validate(*_part_xy(s, d), 3).withColumn("sse", F.round(F.col("sse") / 1000, 3)))


# surroundings: tokens, one pass over all lines, set operations on supports
query("tokens_of_benchmark", "SELECT item_id AS rid, CAST(count(*) AS DOUBLE) AS val FROM (SELECT item_id, unnest(string_split(text, ' ')) AS w FROM benchmark) GROUP BY 1")(lambda s, d: from_tokens(table(s, d, "benchmark"), "item_id", "text")[0].groupBy("rid").agg(F.sum("val").alias("val")))
query("all_lines_at_once", f"{_with('TNN')} SELECT coalesce(rid, -1) AS rid, coalesce(cid, -1) AS cid, sum(val) AS val FROM tnn GROUP BY GROUPING SETS ((rid), (cid), ())")(lambda s, d: _lines(_tnn(s, d)))
query("support_in_both", f"{_with('CUE', 'CUH')} SELECT rid, cid FROM cue INTERSECT SELECT rid, cid FROM cuh")(lambda s, d: _cue(s, d).cells().select("rid", "cid").intersect(_cuh(s, d).cells().select("rid", "cid")))
query("label_counts", f"{_with('YLB')} SELECT cid, count(*) AS stored, CAST(count(*) FILTER (val <> 0) AS BIGINT) AS nonzero FROM ylb GROUP BY cid")(lambda s, d: _ylb(s, d).cells().groupBy("cid").agg(F.count("*").alias("stored"), F.count_if(F.col("val") != 0).alias("nonzero")))


def _lines(m: Matrix) -> DataFrame:
    m.create_view("__lines")
    return m.spark.sql("SELECT coalesce(rid, -1L) AS rid, coalesce(cid, -1L) AS cid, sum(val) AS val FROM __lines GROUP BY GROUPING SETS ((rid), (cid), ())")
