"""The registered queries of this subpackage, each over its whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from gridalg.functions.ship import ship


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def pseudonym_key(spark: SparkSession) -> str:
    """The session's spark.gridalg.pseudonym.key. Only trials on synthetic tables go without: their key is no secret."""
    return spark.conf.get("spark.gridalg.pseudonym.key", "trial key, no secret")


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gridalg.llm import decontaminate as m

    return m.digest(m.find_windows(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))


def op2_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from gridalg.llm import piecefst as m

    return m.encode_decode(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from gridalg.llm import pii as m

    out = m.pseudonymise(table(spark, sf_dir, "documents").select("doc_id", "text"), key=pseudonym_key(spark), spans=True)
    spans = F.array_join(F.transform("pii_spans", lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    return out.select("doc_id", F.size("pii_spans").cast("long").alias("n_found"), spans.alias("spans"), F.sha2("text", 256).alias("text_sha256"), "text")


def op4_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gridalg.llm import minhash as m

    return m.near_duplicates(table(spark, sf_dir, "documents"), shingle=2)


def op5_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gridalg.llm import neighbours as m

    return m.nearest(table(spark, sf_dir, "embeddings"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from gridalg.llm import tokencount as m

    return m.count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from gridalg.llm import suffixdedup as m

    out = m.remove_repeats(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), "kept_sha256")


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gridalg.llm import toxicity as m

    return m.score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gridalg.llm import extract as m

    return m.extract(table(spark, sf_dir, "pages"))


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gridalg.llm import secrets as m

    return m.digest(m.scan(table(spark, sf_dir, "documents")))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, f in globals().items() if k.startswith("op") and k[2].isdigit()}


def oracle_sql() -> dict[str, str]:
    from gridalg.llm import oracles

    return dict(oracles.ORACLES)
