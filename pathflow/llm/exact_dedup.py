"""Exact duplicates: 128-bit content hash, then bytes inside groups, then one row stays.

Every row gets the 128-bit hash (and, for the result, the SHA-256) of its normalised text in one pass; hashes, not texts, are grouped. A hash that
one row has is a class of its own, whose text never crosses the network. Rows that share a hash are compared byte by byte: grouped
by the hash *and* the normalised text, with copies combined before the shuffle, so that a text that makes up a third of all rows crosses the network
once a task and two texts with one hash stay two classes. Classes go back to their rows by both hashes, in a join that adaptive execution may split on hot texts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, discard, materialize

#: Shared hashes up to this many (24 bytes each) are broadcast to the pass that picks the texts to compare; more are joined by a shuffle.
BROADCAST_HASHES = 1_000_000
BEST = {"min": F.min, "max": F.max}


def _norm(text_col: str) -> Column:
    return ascii_lower(F.coalesce(F.col(text_col), F.lit("")))


def _h128(norm: Column) -> Column:
    return F.unhex(F.md5(norm.cast("binary")))


def _sha(norm: Column) -> Column:
    return F.unhex(F.sha2(norm.cast("binary"), 256))


def exact_classes(docs: DataFrame, digests: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """One row per distinct normalised text that shares its 128-bit hash with another row: h128, sha (of the text), keep_id, group_size.

    digests (id, h128): of all rows. keep: 'min' or 'max' id stays. Null text counts as empty; null ids never win while another id exists.
    """
    shared = materialize(digests.groupBy("h128").agg(F.count("*").alias("n")).where("n > 1").select("h128"), "shared")
    if shared.count() <= BROADCAST_HASHES:
        shared = F.broadcast(shared)
    rows = docs.select(F.col(id_col).alias("id"), _norm(text_col).alias("norm")).withColumn("h128", _h128(F.col("norm")))
    classes = rows.join(shared, "h128", "left_semi").groupBy("h128", "norm").agg(BEST[keep]("id").alias("keep_id"), F.count("*").alias("group_size"))
    return classes.select("h128", _sha(F.col("norm")).alias("sha"), "keep_id", "group_size")


ADDED = ("keep_id", "group_size", "kept", "text_sha256")


def mark_exact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", columns: list[str] | None = None) -> DataFrame:
    """Rows of `docs` (all columns, or `columns`) with keep_id, group_size, kept, text_sha256; columns of these names are replaced, others may have any name.

    Null texts are empty ones, whatever their length texts are whole. Empty table: no rows. Rows that repeat both id and text are one document and share `kept`.
    """
    names = [c for c in (docs.columns if columns is None else columns) if c not in ADDED]
    norm = _norm(text_col)
    row = docs.select(F.struct(*[F.col(c) for c in names]).alias("row"), F.col(id_col).alias("id"), _h128(norm).alias("h128"), _sha(norm).alias("sha"))
    row = materialize(row, "digests")
    classes = exact_classes(docs, row.select("h128"), id_col, text_col, keep)
    joined = row.join(classes, ["h128", "sha"], "left")
    size = F.coalesce("group_size", F.lit(1))
    keep_id = F.when(F.col("group_size").isNull(), F.col("id")).otherwise(F.col("keep_id"))
    out = joined.withColumn("k", keep_id)
    return out.select(*[F.col("row")[c].alias(c) for c in names], F.col("k").alias("keep_id"), size.alias("group_size"), F.col("id").eqNullSafe(F.col("k")).alias("kept"), F.lower(F.hex("sha")).alias("text_sha256"))


def drop_exact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "max") -> DataFrame:
    """The rows that stay, with the columns of `docs`. Rows that repeat an id and a text leave one row, of which the other columns may be any of theirs.

    Ids and digests of the rows that go are taken out of `docs`: in place while they are few enough for a broadcast, else by a shuffle on id and digest.
    """
    norm = _norm(text_col)
    digests = materialize(docs.select(F.col(id_col).alias("id"), _h128(norm).alias("h128"), _sha(norm).alias("sha")), "digests")
    classes = exact_classes(docs, digests, id_col, text_col, keep)
    goes = digests.join(classes, ["h128", "sha"]).where(~F.col("id").eqNullSafe(F.col("keep_id"))).select(F.col("id").alias("gone_id"), F.col("sha").alias("gone_sha"))
    goes = materialize(goes.distinct(), "goes")
    repeated = not digests.groupBy("id", "sha").count().where("count > 1").isEmpty()
    discard(digests)
    if goes.count() <= BROADCAST_HASHES:
        goes = F.broadcast(goes)
    marked = docs.select(F.struct(*docs.columns).alias("row"), F.col(id_col).alias("id"), _sha(norm).alias("sha"))
    stay = marked.join(goes, marked.id.eqNullSafe(F.col("gone_id")) & (marked.sha == F.col("gone_sha")), "left_anti")
    if repeated:
        stay = stay.dropDuplicates(["id", "sha"])
    return stay.select("row.*")
