"""The registered queries of this subpackage, one for each operator."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from . import avi, bpe, chat, hmm, mixing, neardup, neighbours, pii, quality, tokens
from .common import read

#: Folder of the public vocabularies; a parameter of every query that needs one.
TOKENIZERS = "/opt/tokenizers"


def op1_avi(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document stored as a motion-JPEG AVI file and read back."""
    return avi.digests(read(spark, sf_dir, "documents"))


def op2_quality(spark: SparkSession, sf_dir: str, sample: int = quality.SAMPLE) -> DataFrame:
    """Quality of every document, learnt from labels that aren't held out."""
    docs = read(spark, sf_dir, "documents")
    return quality.score(docs, quality.train(docs, read(spark, sf_dir, "labels"), sample))


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Personal data of every document."""
    return pii.find(read(spark, sf_dir, "documents"))


def op4_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every conversation formatted, and read back from the output."""
    probe = spark.sql("SELECT -7L AS conv_id, turn, role, :text AS text FROM VALUES (0L, 'user'), (1L, 'assistant') AS t(turn, role)", args={"text": chat.PROBE})
    turns = read(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(probe)
    return chat.digests(chat.conversations(chat.linear(turns)))


def op5_hmm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document scored by a hidden Markov model of those that aren't held out."""
    docs = hmm.split(read(spark, sf_dir, "documents").select("doc_id", "text"))
    return hmm.score(docs, docs.where("NOT held_out"))


def op6_bpe(spark: SparkSession, sf_dir: str, path: str = os.path.join(TOKENIZERS, "byte_bpe_50k.json")) -> DataFrame:
    """Every document encoded, and decoded from its ids."""
    return bpe.round_trip(read(spark, sf_dir, "documents"), path)


def op7_neighbours(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """The nearest other vectors of every hundredth vector."""
    vectors = read(spark, sf_dir, "embeddings")
    return neighbours.search(neighbours.build(vectors), vectors.where("vec_id % 100 = 0"), k)


def op8_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words that the mix takes of every document and where its copies begin, in order of training."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "source", "text")
    copies = F.size("positions")
    last = F.when(copies > 0, F.element_at("positions", -1))
    return mixing.mix(docs, keep=["doc_id"]).select("row.doc_id", "size", "source_size", "target", "taken", copies.cast("long").alias("n_copies"), "first_position", last.alias("last_position"))


def op9_tokens(spark: SparkSession, sf_dir: str, path: str = os.path.join(TOKENIZERS, "byte_bpe_50k.json"), rule: str = "first") -> DataFrame:
    """Tokens of every line of every document."""
    return tokens.sections(read(spark, sf_dir, "documents"), path, rule)


def op10_neardup(spark: SparkSession, sf_dir: str, words: int = 2, percent: int = 80) -> DataFrame:
    """Component of near-duplicates of every document."""
    return neardup.components(read(spark, sf_dir, "documents"), words, percent)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_avi": op1_avi,
    "op2_quality": op2_quality,
    "op3_pii": op3_pii,
    "op4_chat": op4_chat,
    "op5_hmm": op5_hmm,
    "op6_bpe": op6_bpe,
    "op7_neighbours": op7_neighbours,
    "op8_mix": op8_mix,
    "op9_tokens": op9_tokens,
    "op10_neardup": op10_neardup,
}

ORACLES: dict[str, str] = {"op4_chat": chat.ORACLE, "op8_mix": mixing.ORACLE, "op10_neardup": neardup.ORACLE}
