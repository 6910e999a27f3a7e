"""Token counts by batch encoding that returns lengths only."""

from __future__ import annotations

import os
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, functions as F

#: Bytes of one call of the tokenizer: bounds what its encodings take, which is many times the text.
BATCH_BYTES = 1 << 18
#: Characters of a text beyond which it is split.
PART_CHARS = 1 << 16


class Counter:
    """Counts of one tokenizer file: .json by tokenizers, .model by sentencepiece."""

    def __init__(self, path: str):
        self.json = path.endswith(".json")
        if self.json:
            os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
            from tokenizers import Tokenizer

            self.tok = Tokenizer.from_file(path)
            self.tok.no_padding()
            self.tok.no_truncation()
            special = [x.content for x in self.tok.get_added_tokens_decoder().values()]
            import json as _json

            with open(path, encoding="utf-8") as f:
                spec = _json.load(f)
            pre = spec.get("pre_tokenizer") or {}
            plain = spec.get("normalizer") is None and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True)
            # Between a letter and a space before a letter, the byte-level pattern ends one piece and starts the next,
            # whatever stands around; special strings are never cut as they hold no such space.
            self.splits = plain and not any(re.search(r"\w \w", x) for x in special)
        else:
            import sentencepiece

            self.tok = sentencepiece.SentencePieceProcessor(model_file=path)
            self.splits = False

    def counts(self, texts: list[str]) -> list[int]:
        if self.json:
            return [len(e.ids) for e in self.tok.encode_batch_fast(texts, add_special_tokens=False)]
        return [len(x) for x in self.tok.encode(texts, num_threads=1)]


_BOUNDARY = re.compile(r"[A-Za-z](?= [A-Za-z])")


def parts(text: str, limit: int = PART_CHARS) -> Iterator[str]:
    """The text cut after letters that a space and a letter follow, into parts of about limit; one without such a place stays whole."""
    at = 0
    while len(text) - at > limit:
        m = _BOUNDARY.search(text, at + limit)
        if not m:
            break
        yield text[at : m.end()]
        at = m.end()
    yield text[at:]


@lru_cache(maxsize=2)
def _counter(path: str) -> Counter:
    return Counter(path)


def _count(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = _counter(path)
        for batch in batches:
            texts = batch.column(1)
            sizes = np.asarray(pa.compute.fill_null(pa.compute.binary_length(texts), 0), np.int64)
            out = np.zeros(len(sizes), np.int64)
            held: list[str] = []
            owner: list[int] = []
            load = 0

            def flush() -> None:
                if held:
                    np.add.at(out, owner, c.counts(held))
                held.clear()
                owner.clear()

            for i in range(len(sizes)):
                if not sizes[i]:
                    continue
                text = texts[i].as_py()
                for p in parts(text) if c.splits else [text]:
                    held.append(p)
                    owner.append(i)
                    load += len(p)
                    if load >= BATCH_BYTES:
                        flush()
                        load = 0
            flush()
            yield pa.record_batch([batch.column(0).cast(pa.int64()), pa.array(sizes), pa.array(out)], names=["doc_id", "n_bytes", "n_tokens"])

    return run


def count_tokens(docs: DataFrame, tokenizer: str, *, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for each document; tokenizer is a file that every executor has.

    Counts are those of the library without begin, end or added special tokens, padding or truncation; special
    strings inside a text are handled as by its default. Null counts as empty: zero bytes and tokens. Rows stay in
    place, repeated ids included; other columns are not read.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    out = rows.mapInArrow(_count(tokenizer), "doc_id long, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)
