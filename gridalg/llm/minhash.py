"""Near-duplicate classes by one-permutation MinHash with optimal densification, banding and star edges.

The plan, in stages that are each linear in rows:

1. A text becomes a set of shingle hashes; one hash of the whole set folds texts with equal sets into one
   representative (the smallest id), however many copies there are.
2. One permutation: the top bits of a shingle's hash choose its bin, the smallest hash of a bin is its value; an
   empty bin borrows from a bin chosen by its own fixed random sequence. Bands of bins are bucket keys.
3. In each bucket one member is the centre, and only the edges centre-member are candidates. The centre is the
   member that meets most others over all its buckets, which in a group of edited copies is the original.
4. Candidates are confirmed on full sets (exact integers), and links are contracted to components.
5. Buckets that still hold several components may hide links between two members neither of which is the
   centre. Their members are searched by rare shingles (see _hidden), exactly and without pairing the members
   of a bucket's main component with each other; what is found is confirmed on full sets as before.

With 32 bands of 4 bins a link of similarity 0.8 shares no bucket with probability 0.5904^32 < 5e-8.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from gridalg.llm import kernel
from gridalg.llm.components import components
from gridalg.llm.lineage import cut

BINS = 128
ROWS = 4
U64 = np.uint64

_EDGES = np.arange(BINS, dtype=U64) << U64(57)
#: For each bin, the bins that it asks in turn when it is empty; the last resort is the first bin that is not empty.
_DONORS = np.random.default_rng(7).integers(0, BINS, (BINS, 96))
_SALT = kernel.mix(np.arange(1, 3 + BINS, dtype=U64))


def signature(shingles: np.ndarray) -> np.ndarray:
    """The densified values of the bins of a sorted set that is not empty."""
    at = np.searchsorted(shingles, _EDGES)
    value = shingles[np.minimum(at, len(shingles) - 1)]
    full = (value >> U64(57)) == np.arange(BINS, dtype=U64)
    empty = np.flatnonzero(~full)
    if len(empty):
        asked = full[_DONORS[empty]]
        donor = _DONORS[empty, asked.argmax(1)]
        donor[~asked.any(1)] = int(full.argmax())
        value[empty] = value[donor]
    return value


def band_keys(sig: np.ndarray, rows: int = ROWS) -> np.ndarray:
    with np.errstate(over="ignore"):
        acc = _SALT[: BINS // rows].copy()
        for k in range(rows):
            acc = kernel.mix(acc * U64(0xD6E8FEB86659FD93) + sig[k :: rows])
        return acc.view(np.int64)


def _sets(batch: pa.RecordBatch, size: int) -> Iterator[tuple[int, np.ndarray]]:
    """Row number and sorted set of shingle hashes; fewer words than a shingle are one shingle."""
    raw, offsets = kernel.buffers(batch.column(1))
    for lo, hi in kernel.pieces(offsets):
        own = offsets[lo : hi + 1] - offsets[lo]
        _, _, h, first = kernel.words(raw[offsets[lo] : offsets[hi]], own, kernel.NONSPACE)
        w, at = kernel.row_windows(h, first, size)
        cut_at = np.searchsorted(at, first)
        for d in range(hi - lo):
            n = int(first[d + 1] - first[d])
            if n >= size:
                yield lo + d, np.unique(w[cut_at[d] : cut_at[d + 1]])
            else:
                yield lo + d, kernel.windows(h[first[d] : first[d + 1]], n) if n else np.zeros(0, U64)


def _sketch(size: int):
    @kernel.tidy
    def run(batches):
        for batch in batches:
            n = batch.num_rows
            count, k1, k2 = np.zeros(n, np.int64), np.zeros(n, U64), np.zeros(n, U64)
            bands: list[np.ndarray] = [np.zeros(0, np.int64)] * n
            with np.errstate(over="ignore"):
                for i, s in _sets(batch, size):
                    count[i] = len(s)
                    if len(s):
                        k1[i], k2[i] = s.sum(), kernel.mix(s ^ _SALT[-1]).sum()
                        bands[i] = band_keys(signature(s))
            lengths = np.concatenate([[0], np.cumsum([len(b) for b in bands])])
            yield pa.record_batch(
                [batch.column(0).cast(pa.int64()), pa.array(count), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), pa.ListArray.from_arrays(pa.array(lengths, pa.int32()), pa.array(np.concatenate([np.zeros(0, np.int64), *bands])))],
                names=["doc_id", "n", "k1", "k2", "bands"],
            )

    return run


def _full(size: int):
    @kernel.tidy
    def run(batches):
        for batch in batches:
            sets = [s.view(np.int64) for _, s in _sets(batch, size)]
            for lo, hi in kernel.pieces(np.concatenate([[0], np.cumsum([8 * len(s) for s in sets])]), 4 << 20):
                part = sets[lo:hi]
                lengths = np.concatenate([[0], np.cumsum([len(s) for s in part])])
                yield pa.record_batch([batch.column(0).slice(lo, hi - lo).cast(pa.int64()), pa.ListArray.from_arrays(pa.array(lengths, pa.int32()), pa.array(np.concatenate([np.zeros(0, np.int64), *part])))], names=["rep", "shingles"])

    return run


def _confirm(pairs: DataFrame, sets: DataFrame, share: tuple[int, int]) -> DataFrame:
    """Those of the pairs (a, b) whose full sets are similar enough."""
    one = pairs.join(sets.select(F.col("rep").alias("a"), F.col("shingles").alias("sa")), "a")
    two = one.join(sets.select(F.col("rep").alias("b"), F.col("shingles").alias("sb")), "b")
    both = F.size(F.array_intersect("sa", "sb"))
    return two.filter(share[1] * both >= share[0] * (F.size("sa") + F.size("sb") - both)).select("a", "b")


#: Sizes within this ratio share a class, for which one prefix length serves.
_CLASS = 1.02


def _hidden(mixed: DataFrame, sets: DataFrame, share: tuple[int, int]) -> DataFrame:
    """Pairs (a, b) of different components of a mixed bucket that may still be links.

    Members of overlapping buckets form a cluster, in which shingles are ordered from rare to common. A link of two
    sizes shares at least `need` shingles, so one of the first size - need + 1 of either set is common to both:
    only these are met, by size class. Shingles of one member alone bound the size of its partners from above.
    """
    num, den = share
    low = mixed.groupBy("h").agg(F.min("rep").alias("b"))
    cluster = components(mixed.join(low, "h").select(F.col("rep").alias("a"), "b").distinct())
    inside = mixed.groupBy("rep").agg(F.first("comp").alias("comp"), F.max(F.col("comp") != F.col("main")).alias("minor"))
    inside = inside.join(cluster, F.col("rep") == F.col("node")).select("rep", "comp", "minor", F.col("component").alias("cluster"))
    token = inside.join(sets, "rep").select("rep", "comp", "minor", "cluster", F.explode("shingles").alias("t"))
    df = token.groupBy("cluster", "t").agg(F.count("*").alias("df"))
    member = token.join(df, ["cluster", "t"]).groupBy("rep", "comp", "minor", "cluster").agg(F.array_sort(F.collect_list(F.struct("df", "t"))).alias("o"), F.count_if(F.col("df") == 1).alias("own"), F.count("*").alias("n"))
    reach = F.floor((F.col("n") - F.col("own")) * (num + den) / F.lit(num)).cast("long") - F.col("n")
    member = cut(member.withColumn("reach", reach).filter(den * F.col("reach") >= num * F.col("n")).select("rep", "comp", "minor", "cluster", "n", "reach", F.col("o.t").alias("o")))

    least_size = F.ceil(F.col("n") * num / F.lit(den)).cast("long")
    most_size = F.least("reach", F.floor(F.col("n") * den / F.lit(num)).cast("long"))
    klass = lambda n: F.floor(F.log(n) / F.log(F.lit(_CLASS))).cast("int")
    need = lambda a, b: F.ceil((a + b) * num / F.lit(num + den)).cast("long")
    met = member.select("cluster", klass(F.col("n")).alias("k"), F.col("rep").alias("b"), F.col("comp").alias("bc"), F.col("n").alias("bn"), F.col("reach").alias("br"), F.posexplode(F.expr(f"slice(o, 1, cast(n - ceil(n * {num} / {den}) + 1 as int))")).alias("bp", "t"))
    asks = member.filter("minor").select("*", F.explode(F.sequence(klass(least_size), klass(most_size))).alias("k"))
    smallest = F.greatest(least_size, F.floor(F.pow(F.lit(_CLASS), F.col("k"))).cast("long") - 1)
    asks = asks.withColumn("p", (F.col("n") - need(F.col("n"), smallest) + 1).cast("int")).filter("p > 0")
    asks = asks.select("cluster", "k", F.col("rep").alias("a"), F.col("comp").alias("ac"), F.col("n").alias("an"), F.col("reach").alias("ar"), F.posexplode(F.expr("slice(o, 1, p)")).alias("ap", "t"))
    fits = (F.col("ac") != F.col("bc")) & (F.col("an") <= F.col("br")) & (F.col("bn") <= F.col("ar")) & (den * F.least("an", "bn") >= num * F.greatest("an", "bn"))
    early = (F.col("ap") <= F.col("an") - need(F.col("an"), F.col("bn"))) & (F.col("bp") <= F.col("bn") - need(F.col("an"), F.col("bn")))
    return asks.join(met, ["cluster", "k", "t"]).filter(fits & early).select("a", "b").distinct()


def near_duplicates(docs: DataFrame, *, shingle: int = 5, share: tuple[int, int] = (80, 100), rows: int = ROWS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each document.

    Words are the runs without ASCII white space, A-Z lower-cased; share is the least similarity as a fraction. A
    document without text or words has an empty set and stands alone; one with fewer words than a shingle has its
    whole sequence as one. Equal texts always fall together. A row without id stands alone: no class, kept. Rows that
    share an id are one document given several times: they share class and fate, and one id must not stand for different
    texts. Other columns are not read; an empty table gives an empty result.
    """
    num, den = share
    if not 0 < num <= den or BINS % rows:
        raise ValueError("share must be in (0, 1], rows must divide the number of bins")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    sketch = cut(texts.mapInArrow(_sketch(shingle), "doc_id long, n long, k1 long, k2 long, bands array<long>"))
    key = ["k1", "k2", "n"]
    reps = sketch.filter("n > 0 AND doc_id IS NOT NULL").groupBy(key).agg(F.min("doc_id").alias("rep"), F.first("bands").alias("bands"))
    banded = reps.select("rep", "n", F.explode("bands").alias("h")).repartition("h")
    shared = banded.groupBy("h").agg(F.count("*").alias("c")).filter("c > 1")
    bucket = cut(banded.join(shared, "h").select("h", "rep", "n", "c"))

    hub = bucket.groupBy("rep").agg(F.sum("c").alias("hub"))
    ranked = bucket.join(hub, "rep")
    centre = ranked.groupBy("h").agg(F.min(F.struct((-F.col("hub")).alias("hub"), "rep", "n")).alias("x")).select("h", F.col("x.rep").alias("centre"), F.col("x.n").alias("cn"))
    near_size = lambda a, b: (den * F.least(a, b) >= num * F.greatest(a, b))
    star = bucket.join(centre, "h").filter((F.col("rep") != F.col("centre")) & near_size(F.col("n"), F.col("cn")))
    star = cut(star.select(F.col("rep").alias("a"), F.col("centre").alias("b")).distinct())

    wanted = bucket.select("rep").distinct()
    sets = cut(texts.join(wanted, texts["doc_id"] == wanted["rep"], "left_semi").mapInArrow(_full(shingle), "rep long, shingles array<long>"))
    links = cut(_confirm(star, sets, share))
    first = cut(components(links))

    placed = bucket.join(first, bucket["rep"] == first["node"], "left").select("h", "rep", "n", F.coalesce("component", "rep").alias("comp"))
    size = placed.groupBy("h", "comp").agg(F.count("*").alias("m"))
    main = size.groupBy("h").agg(F.count("*").alias("comps"), F.max(F.struct("m", "comp")).alias("x")).filter("comps > 1").select("h", F.col("x.comp").alias("main"))
    mixed = cut(placed.join(main, "h"))
    rest = _hidden(mixed, sets, share).join(star, ["a", "b"], "left_anti")
    more = cut(_confirm(rest, sets, share))

    final = first if more.isEmpty() else components(first.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(more))
    rep_of = reps.select(*key, "rep").join(final, F.col("rep") == F.col("node"), "left").select(*key, F.coalesce("component", "rep").alias("component_id"))
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id"))
    out = sketch.select("doc_id", *key).join(rep_of, key, "left").select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def deduplicate(docs: DataFrame, *, shingle: int = 5, share: tuple[int, int] = (80, 100)) -> DataFrame:
    """One document of each class of near-duplicates: the one with the smallest doc_id, all its columns as they were.

    Rows without id, without text or without words stay; rows that share an id stay or go together.
    """
    gone = near_duplicates(docs, shingle=shingle, share=share).filter(~F.col("kept")).select("doc_id")
    return docs.join(gone, "doc_id", "left_anti").select(docs.columns)
