"""Headline queries, methods against baselines: prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
RUNS = int(os.environ.get("BENCH_RUNS", "2"))


def main() -> None:
    from pyspark.sql import SparkSession, functions as F

    from gridalg import baselines, measure, queries as q
    from gridalg.algos import pnmf as nmf
    from gridalg.algos.regress import gram, linreg, linreg_row
    from gridalg.api import Engine, Limits, Matrix, Scheme
    from gridalg.functions.lineage import cut
    from gridalg.functions.merge import ADD, MUL

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    def held(name: str) -> Matrix:
        """A stand-in with its entries written and measured, as a loaded matrix is."""
        m = q.MATRICES[name](spark, SF)
        return Matrix.of(cut(m.cells()), *m.shape, stats=True, name=name)

    m = {k: held(k) for k in ("QPS", "QCP", "TNN", "EMB", "CUE", "CUH", "QOL")}
    none = Engine(rules=frozenset())
    qps, qcp, tnn = m["QPS"], m["QCP"], m["TNN"]
    one = Matrix.of(qps.cells().groupBy("rid").agg(F.sum("val").alias("val")).select("rid", F.lit(0).cast("long").alias("cid"), "val"), qps.shape[0], 1)
    x3 = Matrix.of(q._pfx(spark, SF).cells().filter("cid < 3"), qps.shape[0], 3)
    big, small = m["QOL"], Matrix.of(m["CUE"].cells(), m["QOL"].shape[0], 7)
    placed = [qps.placed(Scheme.R), qps.placed(Scheme.R)]
    cost, hours = q._cost(spark, SF), m["CUH"]
    cost = Matrix.of(cut(cost.cells()), *cost.shape, stats=True, name="COST")
    turned = Matrix.of(cut(hours.T.cells()), hours.shape[1], hours.shape[0], stats=True, name="CUHT")
    chunks = [baselines.chunked(big), baselines.chunked(small)]
    grid, f_qps = nmf.prepare(qcp, 10), nmf.start(qps, 10)
    grid_qps = nmf.prepare(qps, 10)
    joined = lambda a, b, **k: a.join(b, "rid=rid", MUL, **k).cells.agg(F.sum("val"))
    f0 = nmf.start(qcp, 10)

    timed = {
        "gram_rowsum": lambda: gram(qps).row_sums().cells(),
        "gram_rowsum_noopt": lambda: gram(qps).row_sums().using(none).cells(),
        "gram_rowsum_product_first": lambda: baselines.product_first(qps, "sum", "r"),
        "gram_rowsum_tuples": lambda: baselines.rdd_rowsum(qps),
        "gram_rowsum_qcp": lambda: gram(qcp).row_sums().cells(),
        "gram_rowsum_qcp_noopt": lambda: gram(qcp).row_sums().using(none).cells(),
        "gram_trace": lambda: gram(qps).trace().cells(),
        "gram_trace_noopt": lambda: gram(qps).trace().using(none).cells(),
        "gram_trace_product_first": lambda: baselines.product_first(qps, "sum", "d"),
        "gram_entry": lambda: gram(qps).entry(1, 1).cells(),
        "gram_entry_product_first": lambda: cut(gram(qps).using(none).cells()).filter("rid = 1 AND cid = 1"),
        "linreg_row_all": lambda: linreg_row(x3, one, 1).cells(),
        **{f"linreg_row_{p}": (lambda e: lambda: linreg_row(x3, one, 1).using(e).cells())(baselines.PROFILES[p]) for p in ("pushdown", "order", "none")},
        "linreg_qps": lambda: linreg(qps, one).cells(),
        "linreg_qps_none": lambda: linreg(qps, one).using(none).cells(),
        "kron_sparse_dense": lambda: q._sxn(spark, SF).kron(tnn).cells(),
        "kron_sparse_dense_densify": lambda: q._sxn(spark, SF).using(Engine(strategy="densify")).kron(tnn).cells(),
        "overlay_add": lambda: big.join(small, "overlay", ADD).cells(),
        "overlay_add_densify": lambda: big.join(small, "overlay", ADD, strategy="densify").cells(),
        "overlay_add_chunks": lambda: baselines.chunk_overlay(*chunks, ADD),
        "overlay_transpose": lambda: qps.join(cost, "transpose", MUL).cells(),
        "overlay_transpose_densify": lambda: qps.join(cost, "transpose", MUL, strategy="densify").cells(),
        "overlay_transpose_users": lambda: hours.join(turned, "transpose", MUL).cells(),
        "overlay_transpose_users_cross": lambda: baselines.cross_overlay(hours, turned, MUL),
        "d2d_rid_rid": lambda: joined(*placed),
        "d2d_rid_rid_unplaced": lambda: joined(baselines.hashed(qps), baselines.hashed(qps)),
        "d2d_users": lambda: joined(hours, hours),
        "d2d_users_cross": lambda: baselines.cross_then_filter(hours, hours, ("rid", "rid"), MUL).agg(F.sum("val")),
        "v2v_sparse": lambda: m["CUE"].join(m["CUH"], "val=val", MUL, strategy="sparse").cells.agg(F.sum("val")),
        "v2v_bloom": lambda: m["CUE"].join(m["CUH"], "val=val", MUL, strategy="bloom").cells.agg(F.sum("val")),
        "pnmf_iteration": lambda: nmf.step(qcp, f0, grid).h,
        "pnmf_iteration_nonzeros": lambda: nmf.step(qcp, f0).h,
        "pnmf_qps": lambda: nmf.step(qps, f_qps, grid_qps).h,
        "pnmf_qps_full_product": lambda: nmf.step_full(qps, f_qps).h,
    }
    seconds = {}
    slow = ("noopt", "first", "tuples", "densify", "cross", "unplaced", "product", "none")  # rivals are run once
    for name, make in timed.items():
        said, s = measure.outcome(make, spark, 60)
        seconds[name] = None if said != "done" else round(s, 3) if s > 5 and name.endswith(slow) else round(measure.timed(make, RUNS, warm=False), 3)
        if said != "done":
            print(name, said, round(s, 1), file=sys.stderr)
    t = time.perf_counter()
    baselines.dense_blocks(qps, "sum", "d", 250)
    seconds["gram_trace_dense_blocks"] = round(time.perf_counter() - t, 3)

    col_placed = qps.placed(Scheme.C)
    e = Engine(limits=Limits(broadcast=0))
    shuffles = {
        "d2d_by_row": measure.shuffled(spark, lambda: joined(placed[0].using(e), placed[1].using(e)))[0],
        "d2d_by_row_and_column": measure.shuffled(spark, lambda: joined(placed[0].using(e), col_placed.using(e)))[0],
        "d2d_hashed": measure.shuffled(spark, lambda: joined(baselines.hashed(qps), baselines.hashed(qps)))[0],
        "d2d_by_column": measure.shuffled(spark, lambda: joined(col_placed.using(e), qps.placed(Scheme.C).using(e)))[0],
    }
    headline = [k for k in ("gram_rowsum", "gram_trace", "gram_entry", "linreg_row_all", "kron_sparse_dense", "overlay_add", "overlay_transpose", "d2d_rid_rid", "v2v_sparse", "pnmf_iteration")]
    ratio = lambda a, b: round(seconds[a] / seconds[b], 2) if seconds.get(a) and seconds.get(b) else None
    print(
        json.dumps(
            {
                "metric": "headline_total",
                "value": round(sum(seconds[k] or 60 for k in headline), 3),
                "unit": "sec",
                "queries": seconds,
                "sf": os.path.basename(SF.rstrip("/")).removeprefix("sf"),
                "shuffle_bytes": shuffles,
                "speedup": {
                    "rowsum_over_product_first": ratio("gram_rowsum_product_first", "gram_rowsum"),
                    "trace_over_product_first": ratio("gram_trace_product_first", "gram_trace"),
                    "trace_over_dense_blocks": ratio("gram_trace_dense_blocks", "gram_trace"),
                    "entry_over_product_first": ratio("gram_entry_product_first", "gram_entry"),
                    "rowsum_over_tuples": ratio("gram_rowsum_tuples", "gram_rowsum"),
                    "overlay_over_densify": ratio("overlay_add_densify", "overlay_add"),
                    "overlay_over_chunks": ratio("overlay_add_chunks", "overlay_add"),
                    "kron_over_densify": ratio("kron_sparse_dense_densify", "kron_sparse_dense"),
                    "transpose_over_densify": ratio("overlay_transpose_densify", "overlay_transpose"),
                    "transpose_over_cross": ratio("overlay_transpose_users_cross", "overlay_transpose_users"),
                    "d2d_over_hashed": ratio("d2d_rid_rid_unplaced", "d2d_rid_rid"),
                    "d2d_over_cross": ratio("d2d_users_cross", "d2d_users"),
                    "linreg_row_over_none": ratio("linreg_row_none", "linreg_row_all"),
                    "linreg_over_none": ratio("linreg_qps_none", "linreg_qps"),
                    "v2v_sparse_over_bloom": ratio("v2v_bloom", "v2v_sparse"),
                    "pnmf_over_full_product": ratio("pnmf_qps_full_product", "pnmf_qps"),
                },
            }
        )
    )


if __name__ == "__main__":
    main()
