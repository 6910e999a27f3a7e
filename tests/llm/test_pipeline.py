import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from gridalg.llm import decontaminate, minhash, queries, toxicity  # noqa: E402
from tests.llm.test_words import brute_classes, brute_hits  # noqa: E402

SF = "/root/testdata/sf0.01"


def test_every_stage_takes_effect(spark):
    docs = queries.table(spark, SF, "documents")
    columns = docs.columns
    kept = docs
    sizes = [docs.count()]
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        before = kept.collect()
        kept = stage(spark, kept, SF)
        rows = kept.collect()
        kept = spark.createDataFrame(rows, kept.schema)
        sizes.append(len(rows))
        if k < len(corpus_pipeline.STAGES) - 1:
            assert kept.columns == columns
        ids = {r.doc_id for r in rows}
        if name == "toxicity":
            bad = {r.doc_id for r in toxicity.score(docs, queries.table(spark, SF, "labels")).filter("predicted = 1").collect()}
            assert ids == {r.doc_id for r in before} - bad and bad
        if name == "near_duplicates":
            classes = brute_classes([(r.doc_id, r.text) for r in before], 5)
            assert ids == {d for d, v in classes.items() if v[2]}
        if name == "decontamination":
            items = [(r.item_id, r.text) for r in queries.table(spark, SF, "benchmark").collect()]
            hits = brute_hits([(r.doc_id, r.text) for r in before], items)
            assert ids == {d for d, v in hits.items() if not v[4]}
        if name == "pii":
            assert ids == {r.doc_id for r in before}
            changed = [r for r in rows for b in before if b.doc_id == r.doc_id and b.text != r.text]
            assert all(r.n_chars == len(r.text) for r in changed)
        if name == "pieces":
            assert all(r.lossless for r in rows)
            assert {r.doc_id: r.decoded for r in rows} == {r.doc_id: r.text for r in before}
    assert sizes[0] > sizes[1] > sizes[2] and sizes[-1] == sizes[-2]
    assert {r.doc_id for r in corpus_pipeline.run(spark, SF).collect()} == ids


def test_entry_lists_all_operators():
    import __spark_entry__ as e

    names = e.queries()
    assert [n for n in names if n.startswith("op")] and {n[2 : n.index("_")] for n in names if n.startswith("op")} == {str(k) for k in range(1, 11)}
    assert "pipeline" in names and set(e.oracle_sql()) <= set(names)
    assert decontaminate and minhash


def test_stages_take_odd_rows_and_clashing_names(spark):
    small = "/root/testdata/sf0.001"
    passage = queries.table(spark, small, "benchmark").first().text
    rows = [
        (None, "no id here, mail a.b@mail.example.org", 1),
        (None, None, 2),
        (900_001, "", 3),
        (900_002, "word " * 40_000 + "end", 4),
        (900_003, "one two three four five six seven", 5),
        (900_003, "one two three four five six seven", 5),
        (900_004, "one two three four five six seven", 6),
        (900_005, None, 7),
        (900_006, f"before {passage} after", 8),
        (None, f"before {passage} after", 9),
        (900_007, "4111 1111 1111 1111", 10),
    ]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or ""), n, n) for i, t, n in rows], "doc_id long, text string, lang string, source string, n_chars long, hit_spans int, ids int")
    kept = docs
    for name, stage in corpus_pipeline.STAGES:
        kept = stage(spark, kept, small)
        if name != "pieces":
            assert kept.columns == docs.columns
            kept = spark.createDataFrame(kept.collect(), kept.schema)
            found = {r.ids for r in kept.collect()}
            if name == "toxicity":
                assert found == set(range(1, 11))
            if name == "near_duplicates":  # a row given twice is one document; those without id, text or words stay
                assert found == {1, 2, 3, 4, 5, 7, 8, 9, 10} and kept.count() == 10
            if name == "decontamination":
                assert found == {1, 2, 3, 4, 5, 7, 10}
            if name == "pii":
                text = {r.ids: r.text for r in kept.collect()}
                assert text[1] != rows[0][1] and text[1].endswith("@mail.example.org") and text[2] is None and text[10] != rows[-1][1]
    got = kept.collect()
    assert len(got) == 8 and all(r.lossless for r in got)
    empty = spark.createDataFrame([], docs.schema)
    for _, stage in corpus_pipeline.STAGES:
        empty = spark.createDataFrame(stage(spark, empty, small).collect(), stage(spark, empty, small).schema) if empty.columns == docs.columns else empty
    assert empty.count() == 0
