"""Helpers: NumPy forms of matrices, and rows as comparable values."""

import os

import numpy as np

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def matrix(spark, x, absent="zero", stats=False, engine=None):
    from gridalg.api import Engine, Matrix

    rows = [(int(i), int(j), None if np.isnan(v) else float(v)) for (i, j), v in np.ndenumerate(np.asarray(x, float)) if np.isnan(v) or v != 0]
    cells = spark.createDataFrame(rows, "rid long, cid long, val double")
    return Matrix.of(cells, *np.shape(x), absent=absent, stats=stats, engine=engine or Engine(), nullable=bool(np.isnan(np.asarray(x, float)).any()))


def array(m, fill=0.0):
    out = np.full(m.shape, fill)
    for r in m.cells().collect():
        out[r.rid, r.cid] = np.nan if r.val is None else r.val
    return out


def duck():
    import duckdb

    c = duckdb.connect()
    c.execute("SET TimeZone='UTC'")
    for t in TABLES:
        p = f"{DATA}/{t}.parquet"
        if os.path.exists(p):
            c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{p}')")
    return c


def plain(rows):
    """Rows as sorted tuples of text, numbers as floats."""
    def one(v):
        if v is None or v != v:
            return "~"
        return repr(float(v)) if isinstance(v, (int, float, np.number)) and not isinstance(v, (bool, np.bool_)) else str(v)

    return sorted(tuple(one(v) for v in r) for r in rows)


def same_as_oracle(spark, run, sql):
    df = run(spark, DATA)
    names = sorted(df.columns)
    rel = duck().execute(sql)
    cols = [d[0] for d in rel.description]
    assert sorted(cols) == names
    want = [tuple(r[cols.index(n)] for n in names) for r in rel.fetchall()]
    got = [tuple(r[n] for n in names) for r in df.collect()]
    assert plain(got) == plain(want)
