"""The corpus pipeline over `documents`: quality, near-duplicates, personal data, mixing, encoding.

Each stage works on all that the one before kept.  The columns of documents stay as they are through the first four
stages; the last returns the encoded mix.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from rasterflow.llm import bpe, mixing, neardup, pii, quality
from rasterflow.llm.common import read, without, written
from rasterflow.llm.queries import TOKENIZERS
from rasterflow.session import ship

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts."""
    ship(spark)
    model = quality.train(docs, read(spark, sf_dir, "labels"))
    return quality.accepted(docs, model)


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates (five words to a shingle, a similarity of 0.8)."""
    ship(spark)
    dropped = written(neardup.components(docs).where("NOT kept").select("doc_id"))
    return without(docs, "doc_id", dropped)


def private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data replaced by its kind."""
    ship(spark)
    out = pii.redact(docs)
    return out.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each copy that the mix takes, in order of training."""
    return mixing.copies(docs).select("row.*")


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows (doc_id, n_tokens, ids) of the mix."""
    ship(spark)
    out = bpe.encode(docs, f"{TOKENIZERS}/byte_bpe_50k.json")
    return out.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), "ids")


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", good),
    ("near_duplicates", distinct),
    ("pii", private),
    ("mixing", mixed),
    ("bpe", encoded),
]

#: The classifier can't be expressed in SQL; tests/llm/test_pipeline.py holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select(*COLUMNS)
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = written(docs)
    return docs
