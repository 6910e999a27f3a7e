"""Least squares over matrices, and QR by rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from gridalg.api import RID, Matrix
from gridalg.functions.lineage import cut


def gram(x: Matrix) -> Matrix:
    return x.T @ x


def linreg(x: Matrix, y: Matrix) -> Matrix:
    """The d x 1 coefficients (X'X)^-1 X'y, written from left to right; the rule of chains has X'y come first."""
    return gram(x).inverse() @ x.T @ y


def linreg_row(x: Matrix, y: Matrix, i: int) -> Matrix:
    """One coefficient; the selection reaches the inverse, so one of its rows meets X'y."""
    return linreg(x, y).select(RID == i)


#: R factors that one task of the reduction stacks.
FAN = 16


def qr(x: Matrix) -> tuple[Matrix, Matrix]:
    """Q and R of a tall matrix. R of each part, then R of stacks of FAN of them until one is left; Q is X R^-1.

    A factor has d x d entries, so a task holds FAN of them; d is bounded by the inverse limit. Needs full column rank.
    """
    m, d = x.shape
    if d > x.engine.limits.inverse:
        raise ValueError(f"QR of {d} columns")
    rows = x.cells().filter("val IS NOT NULL").groupBy("rid").agg(F.collect_list(F.struct("cid", "val")).alias("e"))

    def factor(frames):
        import numpy as np
        import pandas as pd

        r = np.zeros((0, d))
        for pdf in frames:
            block = np.zeros((len(pdf), d))
            for i, entries in enumerate(pdf["e"]):
                for e in entries:
                    block[i, e["cid"]] = e["val"]
            r = np.linalg.qr(np.vstack([r, block]), mode="r")
        if len(r):
            yield pd.DataFrame({"part": [r.ravel().tolist()]})

    def stack(pdf):
        import numpy as np
        import pandas as pd

        r = np.linalg.qr(np.vstack([np.array(p).reshape(-1, d) for p in pdf["part"]]), mode="r")
        return pd.DataFrame({"n": pdf["n"].iloc[:1] // FAN, "part": [r.ravel().tolist()]})

    def signed(frames):
        import numpy as np
        import pandas as pd

        for pdf in frames:
            for p in pdf["part"]:
                r = np.array(p).reshape(-1, d)
                r = np.vstack([r, np.zeros((d - len(r), d))]) if len(r) < d else r
                r = r * np.where(np.diag(r) < 0, -1.0, 1.0)[:, None]
                i, j = np.triu_indices(d)
                yield pd.DataFrame({"rid": i, "cid": j, "val": r[i, j]})

    local = cut(rows.mapInPandas(factor, "part array<double>").withColumn("n", F.spark_partition_id().cast("long")))
    left = local.agg(F.max("n")).first()[0]
    while left:  # log of the number of parts to the base FAN
        local = local.groupBy(F.floor(F.col("n") / FAN).alias("g")).applyInPandas(stack, "n long, part array<double>")
        left //= FAN
    r = Matrix.of(local.mapInPandas(signed, "rid long, cid long, val double"), d, d, engine=x.engine)
    return x @ r.inverse(), r


def cross_validate(x: Matrix, y: Matrix, k: int, seed: int | None = None) -> DataFrame:
    """fold, n, squared error of least squares trained without the fold; fold is the row id modulo k or a seeded hash."""
    out = None
    for i, ((tx, vx), (ty, vy)) in enumerate(zip(x.kfold(k, seed), y.kfold(k, seed), strict=True)):
        guess = (vx @ linreg(tx, ty)).cells().select("rid", F.col("val").alias("p"))
        err = vy.cells().join(guess, "rid", "left").agg(F.count("*").alias("n"), F.sum(F.pow(F.col("val") - F.coalesce("p", F.lit(0.0)), 2)).alias("sse")).select(F.lit(i).alias("fold"), "n", "sse")
        out = err if out is None else out.unionByName(err)
    return out
