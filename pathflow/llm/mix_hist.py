"""Mixing sources to target weights: nested budget thresholds on hash histograms, without sorting.

Every document has a fixed 60-bit hash. Sizes are summed by source and hash bucket; the bucket in which a source's budget ends is
the only one refined, ten bits at a time, until it holds one hash value. The mix then is a filter `hash < cut`. A larger budget moves the
cut up only, so mixes nest. What each step aggregates is at most 1024 rows a source; documents are never ranked.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import WORD, discard, materialize

HASH_BITS, STEP_BITS = 60, 10
#: Weights of the sources in order, repeating.
WEIGHTS = (3, 1, 2)


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def document_hash(doc_id: Column, seed: str = "mix") -> Column:
    """60 bits of an md5 of the id: the same in every engine and run."""
    return F.conv(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit(""))).cast("binary")).substr(1, HASH_BITS // 4), 16, 10).cast("long")


def source_targets(sized: DataFrame, percent: int = 150, cap: int = 2, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """(source, size) rows -> source, source_size, target; one row a source.

    The sources share percent/100 of all sizes by weight; a target stops at `cap` times its source's size and the excess goes to
    the others by weight until none is above. Sources are ordered by code point, null last, on their totals: one small row each.
    """
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    place = F.row_number().over(W.orderBy(F.col("source").isNull(), F.col("source")))
    table = materialize(totals.withColumn("place", place).withColumn("weight", F.element_at(F.array(*[F.lit(w) for w in weights]), ((F.col("place") - 1) % len(weights) + 1).cast("int"))), "sources")
    capped, free = 0, -1  # words of capped sources; weight of the others
    total = table.agg(F.sum("source_size")).first()[0] or 0
    budget = total * percent / 100
    over = F.lit(False)
    while True:
        limit = F.col("source_size") * cap
        sums = table.agg(F.sum(F.when(over, limit)).alias("c"), F.sum(F.when(~over, F.col("weight"))).alias("w")).first()
        c, w = sums["c"] or 0, sums["w"] or 0
        if (c, w) == (capped, free) or not w:
            break
        capped, free = c, w
        over = F.lit(budget - capped) * F.col("weight") / F.lit(free) > limit
    share = F.lit(float(budget - capped)) * F.col("weight") / F.lit(free)
    return table.select("source", "source_size", F.when(over, limit.cast("double")).otherwise(share).alias("target"))


def hash_cuts(docs: DataFrame, budgets: DataFrame) -> DataFrame:
    """docs (source, size, h), budgets (source, budget) -> source, cut: documents with h < cut sum to the budget or just below.

    A document whose size would overstep the budget is left out; documents with one hash stay together.
    """
    state = budgets.select("source", F.col("budget").cast("double").alias("left"), F.lit(0).cast("long").alias("base"))
    for shift in range(HASH_BITS - STEP_BITS, -1, -STEP_BITS):
        here = state.withColumnRenamed("source", "_s")
        offset = F.shiftrightunsigned(F.col("h") - F.col("base"), shift)
        inside = docs.join(here, docs.source.eqNullSafe(F.col("_s"))).where((F.col("h") >= F.col("base")) & (offset < 2**STEP_BITS))
        hist = inside.groupBy("source", "left", "base", offset.alias("b")).agg(F.sum("size").alias("words"))
        w = W.partitionBy("source").orderBy("b")
        upto = hist.withColumn("upto", F.sum("words").over(w)).where(F.col("upto") <= F.col("left"))
        # the last bucket that fits whole, and what fits before the next one
        fits = upto.groupBy("source").agg(F.max("b").alias("last"), F.max("upto").alias("used")).withColumnRenamed("source", "_s")
        over = hist.withColumn("upto", F.sum("words").over(w)).where(F.col("upto") > F.col("left")).groupBy("source").agg(F.min("b").alias("next")).withColumnRenamed("source", "_t")
        joined = state.join(fits, state.source.eqNullSafe(F.col("_s")), "left").join(over, state.source.eqNullSafe(F.col("_t")), "left")
        # no bucket oversteps: everything from here on fits, so the cut is at the end of the interval
        step = F.coalesce(F.col("next"), F.lit(2**STEP_BITS if shift == HASH_BITS - STEP_BITS else 2**STEP_BITS))
        fresh = materialize(joined.select("source", (F.col("left") - F.coalesce("used", F.lit(0))).alias("left"), (F.col("base") + F.shiftleft(step.cast("long"), shift)).alias("base"), F.col("next").isNotNull().alias("open")), "cuts")
        discard(state)
        state = fresh
        if state.where("open").isEmpty():
            break
    return state.select("source", F.col("base").alias("cut"))


def mix(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", percent: int = 150, cap: int = 2, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """doc_id, source, size (words), source_size, target, copies, taken (= copies * size).

    A source takes whole rounds of all its documents and, for what is left of its target, those below its hash cut. Null texts have size 0;
    null sources are one source, the last; an empty table gives no rows. Documents that repeat an id are taken together. Reruns agree.
    """
    rows = materialize(docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), word_count(F.col(text_col)).alias("size"), document_hash(F.col(id_col)).alias("h")), "sizes")
    targets = source_targets(rows, percent, cap, weights)
    rounds = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    plan = materialize(targets.withColumn("rounds", rounds).withColumn("budget", F.col("target") - F.col("rounds") * F.col("source_size")), "plan")
    cuts = hash_cuts(rows, plan.where("rounds < " + str(cap)).select("source", "budget")).withColumnRenamed("source", "_c")
    plan = materialize(plan.join(cuts, plan.source.eqNullSafe(F.col("_c")), "left").select(F.col("source").alias("_s"), "source_size", "target", "rounds", F.coalesce("cut", F.lit(0)).alias("cut")), "plan")
    out = rows.join(plan, rows.source.eqNullSafe(F.col("_s")))
    copies = F.col("rounds") + (F.col("h") < F.col("cut")).cast("long")
    return out.select(F.col("id").alias(id_col), "source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"))
