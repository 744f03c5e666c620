"""Corpus pipeline: language ID, exact dedup, MinHash near-dedup, source mixing, byte-level BPE.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; run() writes each stage's rows as Parquet in the
shared folder and reads them again for the next. All stages but the last return the columns of `docs`; columns beside doc_id, text, lang and source may have
any name. Empty tables give empty tables.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe_replay, exact_dedup, langid_rank, mix_hist, superminhash
from .common import discard, fresh, materialize, table

#: A document is rejected without a letter, or if it is this far from every language profile.
LEAST_SCORE = 0.15


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Learns the profiles from the documents themselves; a kept row whose lang is null gets the predicted one. Null and wordless texts go; repeats and
    ties stay or go together."""
    pred, score, gap = names = fresh(docs.columns, "pred", "score", "gap")
    found = langid_rank.identify(docs, langid_rank.language_profiles(docs), names=tuple(names))
    kept = found.where((F.col(pred) != "und") & (F.col(score) >= LEAST_SCORE))
    return kept.withColumn("lang", F.coalesce("lang", pred)).select(*docs.columns)


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts (A-Z lower-cased, null as empty) the row with the largest doc_id stays; rows that repeat it leave one."""
    return exact_dedup.drop_exact(docs, keep="max")


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Five-word shingles, similarity 0.8; the least id of each group stays, as do null texts, null ids and all rows that repeat a kept id."""
    (gone,) = fresh(docs.columns, "gone")
    groups = superminhash.near_duplicate_components(docs, shingle=5, percent=80).where("NOT kept AND doc_id IS NOT NULL").select(F.col("doc_id").alias(gone)).distinct()
    return docs.join(groups, docs.doc_id == F.col(gone), "left_anti")


def mix_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A document that the mix takes twice stands twice; one that it does not take goes. Rows that repeat an id are taken together; null sources are one."""
    key, copies, copy = fresh(docs.columns, "key", "copies", "copy")
    taken = mix_hist.mix(docs).groupBy("doc_id").agg(F.max("copies").alias(copies)).where(F.col(copies) > 0).withColumnRenamed("doc_id", key)
    joined = docs.join(taken, docs.doc_id.eqNullSafe(F.col(key)))
    return joined.withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(copies).cast("int")))).select(*docs.columns)


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every row; null texts have no tokens."""
    return bpe_replay.encode_digests(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [("language_id", language_stage), ("exact_dedup", exact_stage), ("near_dedup", near_stage), ("mix_sources", mix_stage), ("byte_bpe", token_stage)]

#: Profiles, signatures and merges have no SQL form; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, last = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
        discard(last)
        last = docs
    return STAGES[-1][1](spark, docs, sf_dir)
