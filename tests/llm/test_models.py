import html
import itertools
import random
import re
import time
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridalg.llm import extract, neighbours, queries, toxicity
from gridalg.llm.oracles import ORACLES
from tests.support import same_as_oracle

RND = random.Random(6)
SF = "/root/testdata/sf0.1"


@pytest.fixture(scope="module")
def model(spark):
    return toxicity.fit(queries.table(spark, SF, "documents"), queries.table(spark, SF, "labels"))


def test_disguises_are_undone(model):
    cases = {"1d10t": "idiot", "stuuupid": "stupid", "m0r0n": "moron", "s t u p i d": "stupid", "i.d.i.o.t": "idiot", "tr@sh": "trash", "$cum": "scum", "p4th3t1c": "pathetic", "w0rthl3ss": "worthless", "l-o-s-e-r": "loser", "idi0t!!": "idiot"}
    for given, want in cases.items():
        x = np.frombuffer(f"the {given} of".encode(), np.uint8)
        assert [toxicity.restore(x[a:b].tobytes().decode(), model.lm) for a, b in toxicity.disguised(x)] == [want]
    for plain in ("the all good", "a b", "anna's book!!!", "end. Next", "x", "wow!!"):
        assert not toxicity.disguised(np.frombuffer(plain.encode(), np.uint8))


def test_decoding_is_the_cheapest_reading(model):
    def cost(options, choice):
        total, x, y = 0.0, 0, 0
        for (add, price) in choice:
            total += price
            for ch in add:
                z = ord(ch) - 96 if ch != " " else 0
                if z == 0 and y == 0:
                    continue
                total -= model.lm[x, y, z]
                x, y = y, z
        return total

    for word in ("c1", "4b", "1o0"):
        options = [[(c, 0.0)] if c.isalpha() else [(y, toxicity.READ) for y in toxicity.IMITATES[c]] + [(" ", toxicity.KEEP)] for c in word] + [[(" ", 0.0)]]
        best = min(itertools.product(*options), key=lambda ch: cost(options, ch))
        assert toxicity.restore(word, model.lm) == "".join(a for a, _ in best).strip()


def test_held_out_accuracy(spark):
    docs, labels = queries.table(spark, SF, "documents"), queries.table(spark, SF, "labels")
    got = toxicity.score(docs, labels)
    assert got.count() == docs.count()
    t = {(r.toxic, r.predicted): r["count"] for r in got.join(labels, "doc_id").filter("held_out").groupBy("toxic", "predicted").count().collect()}
    assert t.get((0, 1), 0) <= 0.01 * t[0, 0]
    assert t[1, 1] >= 0.85 * (t[1, 1] + t[1, 0])  # one in twenty labels is on a text that nothing tells from clean ones
    words = "idiot stupid moron trash worthless pathetic clown loser scum disgusting".split()
    told = sum(F.lower("text").rlike(rf"\b{w}\b").cast("int") for w in words)
    assert got.join(docs.filter(told >= 3).select("doc_id"), "doc_id").filter("predicted = 0").count() == 0


def test_held_out_accuracy_on_a_tenth_of_the_rows(spark):
    small = "/root/testdata/sf0.01"  # some 40 toxic labels to learn from
    docs, labels = queries.table(spark, small, "documents"), queries.table(spark, small, "labels")
    t = {(r.toxic, r.predicted): r["count"] for r in toxicity.score(docs, labels).join(labels, "doc_id").filter("held_out").groupBy("toxic", "predicted").count().collect()}
    assert t[1, 1] >= 0.7 * (t[1, 1] + t.get((1, 0), 0)) and t.get((0, 1), 0) <= 0.01 * t[0, 0]


def test_rows_are_judged_one_by_one(spark):
    docs, labels = queries.table(spark, SF, "documents"), queries.table(spark, SF, "labels")
    bad, fine = "you stupid idiot, pathetic moron and worthless loser", "the table was on and of"
    odd = [(None, bad, 1), (None, fine, 2), (3, bad, 3), (3, bad, 3), (3, fine, 3), (5, None, 4)]
    more = spark.createDataFrame([(-1 - i, *r) for i, r in enumerate(odd)], "n long, doc_id long, text string, score int").drop("n")
    got = toxicity.drop_toxic(docs.select("doc_id", "text", F.lit(0).alias("score")).unionByName(more), labels)
    assert sorted(map(str, got.filter("score > 0").collect())) == sorted(map(str, more.filter("text is null or text like 'the%'").collect()))
    held = toxicity.score(docs.select("doc_id", "text").unionByName(more.select("doc_id", "text")), labels).filter("doc_id is null").collect()
    assert len(held) == 2 and not any(r.held_out for r in held)


def test_disguised_words_score_like_plain_ones(spark, model):
    docs = spark.createDataFrame([(0, "the m0r0n was s t u p i d"), (1, "the moron was stupid"), (2, "the table was on and of"), (3, None), (4, ""), (5, "x " * 100_000)], "doc_id long, text string")
    held = spark.sparkContext.broadcast(model)
    s = {r.doc_id: r.score for r in docs.mapInArrow(toxicity._score(held), "doc_id long, score double").collect()}
    assert s[0] == pytest.approx(s[1]) and s[0] > 0.7 > s[2] and s[3] == s[4] == pytest.approx(s[2])


def test_disguises_in_letters_with_accents(spark, model):
    cases = {"C0D\u00c9": "cod\u00e9", "p r e\u0301 t e": "pr\u00e9te", "sch\u00f6\u00f6\u00f6n": "sch\u00f6n", "n1\u00f1o": "ni\u00f1o"}
    got = {t: more for t in cases for _, _, more, _ in toxicity.readings(toxicity.pa.array([f"le {t}."]), model)}
    assert got == {t: [w] for t, w in cases.items()}
    texts = ["Stra\u00dfe \u00c0 b", "", "E\u0301\U0001f600x", "plain"]
    part, at, points, to = toxicity.folded(*toxicity.kernel.buffers(toxicity.pa.array(texts)))
    want = ["stra\u00dfe \u00e0 b", "", "\u00e9\U0001f600x", "plain"]
    assert [part[a:b].tobytes().decode() for a, b in itertools.pairwise(at)] == want and [toxicity._text(points[a:b]) for a, b in itertools.pairwise(to)] == want


def test_long_spans_and_wide_spacing_are_read_whole(model):
    words = ["you", "are", "such", "a", "stupid", "idiot", "and", "pathetic", "loser"] * 9
    cases = {"  ".join(" ".join(w) for w in words): " ".join(words), "s  t  u  p  i  d": "stupid", "s - t - u - p - i - d": "stupid", "i. d. i. o. t": "idiot"}
    for t, want in cases.items():
        x = np.array([ord(c) for c in f"word {t} word"])
        assert [toxicity.restore(toxicity._text(x[a:b]), model.lm) for a, b in toxicity.disguised(x)] == [want]


def test_only_texts_of_one_word_set_are_copies(spark, model):
    texts = [f"{w} word{i}" for i in range(400) for w in ("zebra", "apple")] + ["word7 Apple apple", "", None]
    held = spark.sparkContext.broadcast(model)
    df = spark.createDataFrame([(t, 1) for t in texts], "text string, toxic int")
    got = df.mapInArrow(toxicity._group(held), "text string, toxic int, grp long, grp2 long")
    assert got.select("grp", "grp2").distinct().count() == 801  # the last but two is a copy, no text is no words


def test_a_long_tail_of_marker_words_is_learned(spark):
    rnd = random.Random(3)
    word = lambda: "".join(rnd.choice("bcdfglmnprst") + rnd.choice("aeiou") for _ in range(3))
    common, marks = [word() for _ in range(200)], [f"z{word()}" for _ in range(60)]
    rows = [(i, " ".join(rnd.choices(common, k=12)) + (f" {marks[i // 5 % 60]}" if i % 5 == 0 else ""), int(i % 5 == 0)) for i in range(4500)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    got = toxicity.score(docs.select("doc_id", "text"), docs.select("doc_id", "toxic"))
    t = {(r.toxic, r.predicted): r["count"] for r in got.join(docs, "doc_id").filter("held_out").groupBy("toxic", "predicted").count().collect()}
    assert t[1, 1] >= 0.9 * (t[1, 1] + t.get((1, 0), 0)) and t.get((0, 1), 0) <= 0.01 * t[0, 0]


def test_of_nested_stems_the_longest_that_explains_as_much_is_kept():
    a = {4: 70, 5: 70, 6: 40, 7: 30, 14: 9, 15: 9}
    assert sorted(toxicity._longest(list(a), a, {}, {5: 4, 6: 5, 7: 5, 15: 14})) == [5, 15]


def test_scores_without_labels_or_documents(spark):
    docs = spark.createDataFrame([(1, "a b", 0.5), (2, None, 0.5)], "doc_id long, text string, score double")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = toxicity.score(docs, labels).collect()
    assert len(got) == 2 and all(r.predicted == 0 and r.score < 0.01 for r in got)
    assert toxicity.score(docs.limit(0), labels).count() == 0
    assert toxicity.drop_toxic(docs, labels).count() == 2
    odd = spark.createDataFrame([(1, 1, None), (1, 1, None), (2, 0, 1)], "doc_id long, quality int, toxic int")
    assert toxicity.score(docs, odd).count() == 2


def test_cut_is_the_least(monkeypatch):
    for _ in range(150):
        n = RND.randint(1, 7)
        own = [(RND.randint(0, 9), RND.randint(0, 9)) for _ in range(n)]
        edges = [(RND.randrange(n), RND.randrange(n), RND.randint(0, 6)) for _ in range(RND.randint(0, 10))]
        edges = [e for e in edges if e[0] != e[1]]
        cost = lambda lab: sum(c if yes else o for (c, o), yes in zip(own, lab, strict=True)) + sum(w for a, b, w in edges if lab[a] != lab[b])
        least = min(cost(lab) for lab in itertools.product((False, True), repeat=n))
        assert cost(extract.cut(own, edges)) == cost(extract.flow_cut(own, edges)) == least


def test_articles_of_the_given_pages(spark):
    pages = queries.table(spark, "/root/testdata/sf0.01", "pages")
    want = {}
    for r in pages.collect():
        a = re.search(r"<article>(.*?)(?:</article>|\Z)", r.html, re.S)
        want[r.page_id] = " ".join(html.unescape(re.sub(r"<[^>]*(?:>|\Z)", " ", a[1].replace("<b>", ""))).split()) if a else ""
    got = {r.page_id: r for r in extract.extract(pages).collect()}
    assert {k: r.text for k, r in got.items()} == want
    assert all(r.n_chars == len(r.text) and r.url for r in got.values())


def overlap(got, want):
    """Precision and recall of words."""
    found = {k: (Counter(got[k].split()), Counter(want[k].split())) for k in want}
    both = sum((a & b).total() for a, b in found.values())
    return both / sum(a.total() for a, _ in found.values()), both / sum(b.total() for _, b in found.values())


def test_pages_whose_declarations_are_removed(spark):
    """Shapes and flow find the article without any region; neither shapes alone nor a wrong classifier do."""
    pages = queries.table(spark, "/root/testdata/sf0.01", "pages")
    odds, regions = extract.fit(pages)
    rows = {r.page_id: r.html for r in pages.collect()}
    want = {k: extract.main_text(h, odds, regions) for k, h in rows.items()}
    bare = {k: re.sub(r" class=\"[^\"]*\"", "", re.sub(r"<(/?)(?:article|nav|footer|header|aside|main)\b", r"<\1div", h)) for k, h in rows.items()}
    precision, recall = overlap({k: extract.main_text(h, odds, regions) for k, h in bare.items()}, want)
    assert precision > 0.99 and recall > 0.99
    # on the pages as they are, a wrong classifier loses text that regions declare; without regions it finds nothing else
    worse = {k: extract.main_text(h, -3 * np.sign(odds), regions) for k, h in rows.items()}
    assert sum(worse[k] != want[k] for k in rows) > len(rows) / 2
    _, recall = overlap({k: extract.main_text(h, -odds, regions) + "_" for k, h in bare.items()}, want)
    assert recall < 0.5
    fitted = extract.fit(spark.createDataFrame([(k, "u", h) for k, h in bare.items()], "page_id long, url string, html string"))
    precision, recall = overlap({k: extract.main_text(h, *fitted) for k, h in bare.items()}, want)
    assert precision > 0.9 and recall > 0.99  # no page declares an article, so shapes keep their prior


def test_flow_settles_blocks_that_their_shape_does_not():
    odds = np.array([[-0.5, 2.0][(i // 48) >= 4] for i in range(extract.SHAPES)])
    long = "A paragraph with many words, and more of them, to make it quite long enough."
    page = f"<div><p>{long}<p>Short.<p>{long}</div><div><ul><li>One<li>Two<li>Three</ul></div>"
    assert extract.main_text(page, odds) == f"{long} Short. {long}"


def test_hostile_pages_of_a_megabyte():
    odds = np.zeros(extract.SHAPES)
    n = 1_000_000
    for page in ("<a " * (n // 3), '<p>x <a href="foo ' * (n // 18), "<a '>" * (n // 5), '<a "x>"' * (n // 7) + '"', "<![CDATA[>" * (n // 10), "</script" * (n // 8), "<div>" * (n // 5) + "x" + "</b>" * (n // 5), "<a " + "b" * n + ">", "&#" + "9" * n + ";", "<p>word " * (n // 8)):
        started = time.time()
        extract.main_text(page, odds)
        assert time.time() - started < 5
    assert extract.main_text("<article>&#0000000000065; &#x0000000041; &#99999999999; &amp;", odds) == "A A \ufffd &"


def test_odd_rows_of_pages(spark):
    page = "<article><p>One, two and three, and more words to make it long.</p></article>"
    df = spark.createDataFrame([(None, None, page, 1), (4, "u", page, 1), (4, "u", page, 1), (5, "v", None, None)], "page_id long, url string, html string, n_chars int")
    got = extract.extract(df).collect()
    assert sorted((r.page_id or 0, r.n_chars) for r in got) == [(0, 51), (4, 51), (4, 51), (5, 0)]


def test_page_parts_that_are_no_article(spark):
    away = """<header>Site</header><nav><ul><li><a href=1>Home</a></ul></nav><aside>Side</aside><div class="cookie-notice">We use cookies</div>
    <div id="ad-top">Buy</div><form><p>Name</p><input></form><script>var x = "<p>no</p>";</script><style>p{}</style><div role="navigation">x</div><p hidden>h</p><!-- c -->"""
    body = "<h1>Title &amp; more</h1><p>First   paragraph,\n with <b>bold</b><i>er</i> text&nbsp;here.<br>line<p>Second one"
    texts = {
        0: (f"<body>{away}<article>{body}<div class='share'>Share</div></article><section class=comments><article>Nice!</article></section><footer>F</footer>", "Title & more First paragraph, with bolder text here. line Second one"),
        1: (f"<body>{away}<main>{body}</main>", "Title & more First paragraph, with bolder text here. line Second one"),
        2: (None, ""),
        3: ("", ""),
        4: ("<nav>only</nav>", ""),
        5: ("<article><p>cut off <a hre", "cut off"),
        6: ("<article>" + "<p>word</p>" * 3000 + "</article>", " ".join(["word"] * 3000)),
        7: ("<article><header><h1>H</h1></header><p>a < b &lt; c</p></article>", "H a < b < c"),
    }
    df = spark.createDataFrame([(k, f"u{k}", h, "x") for k, (h, _) in texts.items()], "page_id long, url string, html string, text string")
    got = {r.page_id: (r.text, r.n_chars) for r in extract.extract(df).collect()}
    assert got == {k: (t, len(t)) for k, (_, t) in texts.items()}
    assert extract.extract(df.limit(0)).count() == 0


def test_pages_without_declared_article():
    odds = np.array([0.02 * (i // 48) - 0.05 for i in range(extract.SHAPES)])
    odds = np.array([[-1.5, 1.5][(i // 48) >= 4] - 1.5 * ((i // 12) % 4 == 3) for i in range(extract.SHAPES)])
    page = "<body>" + "".join(f"<p>paragraph {i} with many words, and more of them, to make it long.</p>" for i in range(4)) + "<ul>" + "".join(f"<li><a href={i}>link</a></li>" for i in range(9)) + "</ul>"
    text = extract.main_text(page, odds)
    assert text.startswith("paragraph 0") and "paragraph 3" in text and "link" not in text


def test_class_words_around_the_article_do_not_hide_it():
    odds = np.array([[-1.5, 3][(i // 48) >= 4] for i in range(extract.SHAPES)])
    text = "A paragraph with many words, and more of them, to make it quite long enough to be read."
    for page in (f"<body class='home has-sidebar'><p>{text}</p>", f"<div id='site'><article>{text}</article></div>", f"<div class='no-sidebar'><main>{text}</main></div>", f"<article class='post tags-x'>{text}</article>", f"<div id='site'><p>{text}</p></div>"):
        assert extract.main_text(page, odds) == text
    around = f"<article>{text}</article><div class='comments'><article>{text}</article></div><div class='sidebar'><p>{text}</p></div>"
    assert extract.main_text(f"<body>{around}", odds) == text


def vectors(n, d=8):
    r = np.random.default_rng(1)
    x = r.integers(-2, 3, (n, d)).astype(float)
    return [(i, [float(v) for v in x[i]], 1) for i in range(n)]


def brute_nearest(rows, k, every):
    ok = [(i, np.array(v)) for i, v, *_ in rows if v and None not in v and np.isfinite(v).all() and any(v)]
    out = {}
    for i, q in ok:
        if i % every == 0:
            near = sorted((float(np.sqrt(((q - x) ** 2).sum())), j) for j, x in ok if j != i and len(x) == len(q))
            out[i] = near[:k]
    return out


@pytest.mark.parametrize("shard", [20_000, 90, 17])
def test_neighbours_against_brute_force(spark, shard):
    rows = vectors(700) + [(1000 + k, [1.0] * 8, 0) for k in range(400)]
    rows += [(2000, None, 0), (2001, [], 0), (2010, [0.0] * 8, 0), (2020, [float("nan")] * 8, 0), (2030, [float("inf")] + [1.0] * 7, 0), (2040, [None] + [1.0] * 7, 0), (2050, [1.0, 2.0], 0), (2060, [2.0, 2.0], 0), (2070, [-0.0, 1.0], 0), (2081, [0.0, 1.0], 0)]
    df = spark.createDataFrame([*rows, rows[10], rows[10], (None, [1.0] * 8, 0)], "vec_id long, embedding array<double>, rank int").repartition(3)
    got = {}
    for r in neighbours.nearest(df, every=10, k=7, shard=shard).collect():
        got.setdefault(r.query_id, {})[r.rank] = (r.score, r.vec_id)
    got = {q: [x[k + 1] for k in range(len(x))] for q, x in got.items()}
    assert got == brute_nearest(rows, 7, 10)


def clusters(n=6000, d=24, groups=40):
    r = np.random.default_rng(5)
    return (r.normal(0, 3, (groups, d))[r.integers(0, groups, n)] + r.normal(0, 0.3, (n, d))).astype(float)


def test_trees_skip_what_the_triangle_inequality_allows(spark):
    x = clusters()
    ids = np.arange(len(x))
    exact = [set(np.lexsort((ids, neighbours.distances(np.repeat(q[None], len(x), 0), x)))[:11].tolist()) for q in x[:60]]
    share = {}
    for factor in (1.0, 1.5, 3.0):
        tree = neighbours.Tree(x)
        name, _ = tree.search(x[:60], 10, factor, ids)
        recall = sum(len(e & set(row.tolist())) for e, row in zip(exact, name, strict=True)) / (11 * 60)
        share[factor] = tree.seen / tree.pairs
        assert recall == 1 if factor == 1 else recall >= 0.9
    assert share[1.0] < 0.3 and share[3.0] < share[1.5] < share[1.0]
    # whole regions are skipped too: queries of one cluster reach few shards
    router = neighbours.Router(x[::4], 16)
    region, far = router.regions(x), router.far(x)
    least, most = (np.array([[f(far[region == g, n], initial=i) for n in range(len(router.nodes))] for g in range(len(router.paths))]) for f, i in ((np.min, np.inf), (np.max, 0)))
    low = router.bounds(x[:60], least, most)
    near = np.array([np.sort(neighbours.distances(np.repeat(q[None], len(x), 0), x))[10] for q in x[:60]])
    for i in range(60):
        assert all(low[i, region[j]] <= near[i] + 1e-9 for j in exact[i])
    assert (low <= near[:, None]).mean() < 0.5
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    full = {(r.query_id, r.vec_id) for r in neighbours.nearest(df, shard=400).collect()}
    assert full == {(q, int(j)) for q in range(0, 6000, 100) for j in np.lexsort((ids, neighbours.distances(np.repeat(x[q][None], len(x), 0), x)))[1:11]}
    loose = {(r.query_id, r.vec_id) for r in neighbours.nearest(df, shard=400, factor=1.5).collect()}
    assert len(full & loose) >= 0.9 * len(full)


def test_small_tables_of_vectors(spark):
    df = queries.table(spark, "/root/testdata/sf0.01", "embeddings")
    with pytest.raises(ValueError):
        neighbours.nearest(df, factor=0.5)
    assert neighbours.nearest(df.limit(0)).count() == 0
    few = spark.createDataFrame([(0, [1.0]), (3, [2.0])], "vec_id long, embedding array<double>")
    assert [tuple(r) for r in neighbours.nearest(few).collect()] == [(0, 1, 3, 1.0)]


@pytest.mark.parametrize("name", ["op1_decontaminate", "op4_minhash", "op5_neighbours"])
def test_queries_give_what_sql_gives(spark, name):
    same_as_oracle(spark, queries.queries()[name], ORACLES[name])
