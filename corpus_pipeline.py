"""A corpus pipeline over documents: quality, near-duplicates, personal data, mixing, pieces.

Every stage works on all that its predecessor kept and returns the columns of
documents; the last adds the encoded form. Quality drops what its rules reject,
near-duplicate removal leaves one document of a class, redaction puts each
personal span as ``[KIND]``, mixing repeats or leaves out documents by the
sources' targets, and the last stage encodes each text and decodes it again.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from plandistill.llm import mixing, neardup, pieces, pii, quality
from plandistill.llm.common import park

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep. Null and empty texts fail them; an empty table stays empty."""
    return quality.judge(docs, columns=COLUMNS).where("kept").select("row.*")


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class (five words, similarity 0.8 or more): the smallest id.
    Rows without id stay; of rows that share an id one stays."""
    return neardup.keep_one(docs.select(*COLUMNS), percent=80)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with each personal span put as ``[KIND]``; n_chars is new where a span was found. Null texts
    stay null."""
    found = pii.find(docs, columns=COLUMNS)
    text = pii.redact(F.col("row.text"), F.col("spans"))
    out = found.select("row.*", text.alias("clean"), F.size("spans").alias("n"))
    return out.select("doc_id", F.col("clean").alias("text"), "lang", "source", F.when(F.col("n") > 0, F.length("clean").cast("long")).otherwise(F.col("n_chars")).alias("n_chars"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; columns beside those of documents are left out."""
    return mixing.repeat(mixing.mix(docs.select(*COLUMNS)))


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document with its piece ids and the text that they decode to (null as the empty text)."""
    import public_tokenizers

    made = pieces.encode_texts(docs, public_tokenizers.path("piece_bpe_32k.model"), ["doc_id", "lang", "source", "n_chars"])
    return made.select("row.doc_id", F.col("decoded").alias("text"), "row.lang", "row.source", "row.n_chars", F.size("ids").cast("long").alias("n_pieces"), "ids")


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("personal_data", personal_data),
    ("mix_sources", mix_sources),
    ("encode_pieces", encode_pieces),
]

#: Boosted trees, MinHash and piece scores have no SQL form; tests/llm compares with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = park(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
