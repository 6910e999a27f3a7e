import pytest

from gridalg import queries
from tests.support import DATA, same_as_oracle

SLOW = {"kron_dd"}


@pytest.mark.parametrize("name", sorted(set(queries.ORACLES) - SLOW))
def test_query_gives_what_sql_gives(spark, name):
    same_as_oracle(spark, queries.QUERIES[name], queries.ORACLES[name])


def test_queries_without_sql_run(spark):
    best = queries.QUERIES["recommend_topk"](spark, DATA).collect()  # held against NumPy in test_engine
    assert {r["rank"] for r in best} == {1, 2, 3, 4, 5} and len({(r.user, r["item"]) for r in best}) == len(best)
    made = {r.join: (r.strategy, r.sa, r.sb) for r in queries.QUERIES["join_choices"](spark, DATA).collect()}
    assert made["QPS QPS rid=rid"] == ("auto", "r", "r") and made["QPS TNN cid=rid"][1:] in (("c", "r"), ("c", "b"), ("r", "b"))


def test_known_answers(spark):
    d = "/root/testdata/sf0.01"
    q = queries.QUERIES
    assert q["gram_trace_qps"](spark, d).first().val == 62798783
    assert q["gram_entry_qps"](spark, d).first().val == 645223
    assert q["gram_entry_ij"](spark, d).first().val == 113301
    assert q["agg_sum_a"](spark, d).first().val == 1524135
    assert q["agg_sum_d"](spark, d).first().val == 60305
    assert q["rule_total_of_product"](spark, d).first().val == 1209562501
    assert q["v2v_miss"](spark, d).count() == 0
    assert q["d2d_rr_ss"](spark, d).first().n == 1374431
    assert q["d2d_cr"](spark, d).first().n == 324575
    assert round(q["linreg_row_lineitem"](spark, d).first().val, 6) == 7.161722
    assert [r.n for r in q["kfold_test"](spark, d).orderBy("fold").collect()] == [11933, 11660, 11935, 12096, 11767]
