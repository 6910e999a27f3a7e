"""A training-corpus pipeline over the documents table: five stages, each one of the operators of gridalg.llm.

Every stage takes all rows that the one before kept. Toxic documents go; of each class of near-duplicates (five-word
shingles, similarity 0.8) the smallest id stays; documents with a benchmark window go; personal data become
pseudonyms; the last stage gives each document's pieces and the text that they decode to.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gridalg.llm import decontaminate, minhash, pii, piecefst, toxicity
from gridalg.llm.lineage import cut
from gridalg.llm.queries import pseudonym_key, table


def _toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.drop_toxic(docs, table(spark, sf_dir, "labels"))


def _near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return minhash.deduplicate(docs, shingle=5, share=(80, 100))


def _decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.decontaminate(docs, table(spark, sf_dir, "benchmark"), mode="document")


def _pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pii.pseudonymise(docs, key=pseudonym_key(spark))


def _pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return piecefst.encode_decode(docs, public_tokenizers.path("piece_bpe_32k.model"))


STAGES = [
    ("toxicity", _toxicity),
    ("near_duplicates", _near_duplicates),
    ("decontamination", _decontaminate),
    ("pii", _pii),
    ("pieces", _pieces),
]

#: Fitted scores and transducer paths are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order; between two of them the rows are written to the shared checkpoint folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = cut(docs)
    return docs
