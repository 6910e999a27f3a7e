"""Secret scans over a trigram inverted index, in DataFrame and SQL functions only.

1. Each rule's regular expression is parsed on the driver into a Boolean query over lower-case trigrams that any
   match must contain: alternatives of conjunctions. A rule without mandatory trigrams has none.
2. One scan posts, for each document, the query trigrams that it holds: (trigram, document). The postings of a
   conjunction are intersected by counting its trigrams in each document.
3. The rules of the candidate documents are verified by their full expressions; rules without mandatory
   trigrams run over every document in the same second scan.
"""

from __future__ import annotations

import re._constants as _c
import re._parser as _p
from dataclasses import dataclass
from functools import reduce
from itertools import product

from pyspark.sql import Column, DataFrame, functions as F

from gridalg.llm.lineage import cut
from gridalg.llm.native import fold, fresh, let

#: Strings at most that one part of an expression may stand for before its query is cut there.
_EXACT = 64
#: Bytes of candidate ids that may be broadcast; more are joined by a shuffle.
BROADCAST_BYTES = 64 << 20


def _any_case(word: str) -> str:
    return "".join(f"[{c}{c.upper()}]" if c.isalpha() else c for c in word)


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    group: int = 0  # the group whose length counts
    least: int = 1


#: The three base rules, then further ones of public token formats. Where an expression may start at each
#: character of a run and reads the run from there, its repeats have a bound (SQL engines take 1,000 at most), so that
#: matching takes linear time.
_WORDS = "|".join(_any_case(w) for w in ("password", "passwd", "secret", "token")) + "|" + _any_case("api") + "_?" + _any_case("key")
BASE = (
    Rule("assign", rf"""({_WORDS})["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    Rule("access", "AKIA[A-Z0-9]+", 0, 20),
    Rule("hex", "[0-9a-f]+", 0, 24),
)
MORE = (
    Rule("private_key", "-----BEGIN [A-Z ]{0,40}PRIVATE KEY[A-Z ]{0,20}-----"),
    Rule("host_token", "gh[pousr]_[A-Za-z0-9]+", 0, 40),
    Rule("chat_token", "xox[abprs]-[A-Za-z0-9-]+", 0, 15),
    Rule("cloud_key", "AIza[0-9A-Za-z_-]+", 0, 39),
    Rule("pay_key", "[sr]k_live_[0-9A-Za-z]+", 0, 24),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{1,1000}\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+", 0, 30),
    Rule("url_login", "[a-z]{1,10}://[A-Za-z0-9._-]+:[A-Za-z0-9._!$*+-]+@", 0, 12),
)
RULES = BASE + MORE

Query = frozenset[frozenset[str]]  # alternatives of conjunctions; one empty conjunction: anything may match
ANY: Query = frozenset([frozenset()])


def _grams(text: str) -> frozenset[str]:
    return frozenset(text[i : i + 3] for i in range(len(text) - 2))


def _both(x: Query, y: Query) -> Query:
    return _reduced({a | b for a in x for b in y})


def _reduced(q) -> Query:
    return frozenset(a for a in q if not any(b < a for b in q))


def _chars(items) -> set[str] | None:
    out: set[str] = set()
    for op, arg in items:
        if op is _c.LITERAL:
            out.add(chr(arg).lower())
        elif op is _c.RANGE and arg[1] - arg[0] < 4:
            out |= {chr(k).lower() for k in range(arg[0], arg[1] + 1)}
        else:
            return None
    return out


def _exact(op, arg) -> set[str] | None:
    """All lower-cased strings that a part stands for, if they are few."""
    if op is _c.LITERAL:
        return {chr(arg).lower()}
    if op is _c.IN:
        return _chars(arg)
    if op is _c.SUBPATTERN:
        return _exact_run(arg[3])
    if op is _c.BRANCH:
        parts = [_exact_run(x) for x in arg[1]]
        return None if None in parts else set().union(*parts)
    if op is _c.MAX_REPEAT and arg[1] is not _c.MAXREPEAT and arg[1] <= 4:
        one = _exact_run(arg[2])
        return one if one is None else {"".join(t) for n in range(arg[0], arg[1] + 1) for t in product(one, repeat=n)}
    return None


def _exact_run(items) -> set[str] | None:
    out = {""}
    for op, arg in items:
        more = _exact(op, arg)
        if more is None or len(out) * len(more) > _EXACT:
            return None
        out = {a + b for a in out for b in more}
    return out


def _query(items) -> Query:
    q, run = ANY, {""}

    def flush(q: Query, run: set[str]) -> Query:
        return _both(q, _reduced({_grams(x) for x in run}))

    for op, arg in items:
        more = _exact(op, arg)
        if more is not None and len(run) * len(more) <= _EXACT:
            run = {a + b for a in run for b in more}
            continue
        q, run = flush(q, run), {""}
        if more is not None:
            run = more
        elif op is _c.SUBPATTERN:
            q = _both(q, _query(arg[3]))
        elif op is _c.BRANCH:
            q = _both(q, _reduced(set().union(*(_query(x) for x in arg[1]))))
        elif op is _c.MAX_REPEAT and arg[0] > 0:
            q = _both(q, _query(arg[2]))
    return flush(q, run)


def trigram_query(pattern: str) -> Query:
    """The alternatives of trigram conjunctions that every match of the pattern meets, in lower case."""
    return _query(_p.parse(pattern))


def candidates(docs: DataFrame, rules: tuple[Rule, ...] = RULES, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, rules: documents whose trigrams allow some rule that has mandatory trigrams, each once."""
    spark = docs.sparkSession
    need = [(r.kind, k, g, len(a)) for r in rules for k, a in enumerate(sorted(map(sorted, trigram_query(r.pattern)))) for g in a]
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.lower(text_col).alias("__low"))
    grams = sorted({x[2] for x in need})
    if not grams:
        return texts.select("doc_id", F.array(F.lit("")).alias("rules")).limit(0)
    has = F.filter(F.array(*[F.when(F.contains(F.col("__low"), F.lit(g)), F.lit(g)) for g in grams]), lambda g: g.isNotNull())
    postings = texts.select("doc_id", F.explode(has).alias("gram"))
    terms = spark.createDataFrame(need, "kind string, part int, gram string, need int")  # as many rows as the rules have trigrams
    met = postings.join(F.broadcast(terms), "gram").groupBy("doc_id", "kind", "part", "need").agg(F.count("*").alias("n"))
    return met.filter("n >= need").groupBy("doc_id").agg(F.collect_set("kind").alias("rules"))


def _spans(text: Column, rule: Rule, order: int) -> Column:
    """array<struct<start, order, end, kind>> of the rule's matches of enough length, from the text between matches and the matches."""
    rx = F.lit(rule.pattern)
    kind = "struct<start:long,order:int,end:long,kind:string>"
    none = F.expr(f"cast(array() as array<{kind}>)")

    def run(x: Column) -> Column:
        def step(at: Column, i: Column) -> Column:
            start = at + F.length(F.get(x["p"], i))
            end = start + F.length(F.get(x["m"], i))
            one = F.array(F.struct(start.alias("start"), F.lit(order).alias("order"), end.alias("end"), F.lit(rule.kind).alias("kind")))
            return F.struct(end.alias("s"), F.when(F.length(F.get(x["g"], i)) >= rule.least, one).otherwise(none).alias("o"))

        return fold(F.size(x["m"]), F.lit(0).cast("long"), step, kind)

    found = F.regexp_extract_all(text, rx, F.lit(0))
    inner = F.regexp_extract_all(text, rx, F.lit(rule.group)) if rule.group else found
    return let(F.struct(F.split(text, rule.pattern, -1).alias("p"), found.alias("m"), inner.alias("g")), run)


def scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and spans array<struct<start, order, end, kind>>, by start and rule order, for each document.

    Positions count code points, ends are exclusive; matches of one rule are leftmost and don't overlap, and those
    that are too short are dropped after matching. Null and empty texts have no spans. Each row has its result, also
    where rows are repeated, share an id or have none: rows of one id are candidates together and verified one by one.
    Other columns are not read; an empty table gives an empty result.
    """
    full = [r for r in rules if frozenset() in trigram_query(r.pattern)]
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    found = cut(candidates(docs, rules, id_col=id_col, text_col=text_col))
    n = found.count()
    small = n * (24 + 16 * len(rules)) <= BROADCAST_BYTES
    found = found.select(F.col("doc_id").alias("id"), "rules")
    joined = texts.join(F.broadcast(found) if small else found, F.col("doc_id").eqNullSafe(F.col("id")), "left")
    none = F.expr("cast(array() as array<struct<start:long,order:int,end:long,kind:string>>)")
    each = []
    for k, r in enumerate(rules):
        # a run of a single class is worth splitting a text for only where it is long enough
        ask = F.col("text").rlike(r.pattern[:-1] + f"{{{r.least},}}") if r in full and r.pattern.startswith("[") and r.pattern.endswith("]+") else (F.lit(True) if r in full else F.array_contains("rules", r.kind))
        each.append(F.when(ask, _spans(F.col("text"), r, k)).otherwise(none))
    return joined.select("doc_id", F.array_sort(reduce(lambda a, b: F.concat(a, b), each)).alias("spans"))


def digest(found: DataFrame) -> DataFrame:
    """Counts of the base kinds, a digest of their spans, and all spans as text."""
    text = lambda spans: F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("spans", lambda x: x["kind"] == k)).cast("long").alias(f"n_{k}")
    base = F.filter("spans", lambda x: x["order"] < len(BASE))
    return found.select("doc_id", *[count(r.kind) for r in BASE], F.sha2(text(base), 256).alias("base_sha256"), text(F.col("spans")).alias("spans"))


def redact(docs: DataFrame, *, mark: str = "[secret]") -> DataFrame:
    """The documents with each union of spans replaced by the mark; others, null texts included, as they were.

    Rows of one id must have one text; rows without id are searched too.
    """
    id_, spans = fresh(docs.columns, "id", "spans")
    found = scan(docs).filter(F.size("spans") > 0).select(F.col("doc_id").alias(id_), F.col("spans").alias(spans)).dropDuplicates([id_])

    def cuts(x: Column) -> Column:
        """The text by characters is sliced, as a substring would count its characters from the start each time."""

        def step(at: Column, i: Column) -> Column:
            y = F.get(spans, i)
            piece = F.concat(F.array_join(F.slice(x, at + 1, F.greatest(y["start"].cast("int") - at, F.lit(0))), ""), F.lit(mark))
            inside = y["start"].cast("int") < at
            return F.struct(F.greatest(at, y["end"].cast("int")).alias("s"), F.when(inside, F.expr("cast(array() as array<string>)")).otherwise(F.array(piece)).alias("o"))

        end = F.array_max(F.transform(spans, lambda y: y["end"])).cast("int")
        tail = F.array_join(F.slice(x, end + 1, F.greatest(F.size(x) - end, F.lit(0))), "")
        return F.concat(F.array_join(fold(F.size(spans), F.lit(0), step, "string"), ""), tail)

    chars = F.filter(F.split("text", ""), lambda c: c != "")
    joined = docs.join(found, F.col("doc_id").eqNullSafe(F.col(id_)), "left")
    return joined.withColumn("text", F.when(F.col(spans).isNull(), F.col("text")).otherwise(let(chars, cuts))).select(docs.columns)
