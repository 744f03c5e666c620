"""Baselines: relational joins, linear and halving search, sparse matrix products, flat collections, plain layouts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.graph import PropertyGraph


def relational_friend_names(spark: SparkSession, person: DataFrame, friend: DataFrame, name: str) -> DataFrame:
    """Names of a person's friends by two joins over three index positions: name, first friend column, identifier."""
    return spark.sql(
        "SELECT b.name AS friend_name, count(*) AS times FROM {person} a JOIN {friend} f ON f.person_a = a.identifier JOIN {person} b ON b.identifier = f.person_b WHERE a.name = :name GROUP BY b.name",
        {"name": name},
        person=person.select(F.col("c_custkey").alias("identifier"), F.col("c_name").alias("name")),
        friend=friend.select(F.col("src").alias("person_a"), F.col("dst").alias("person_b")),
    )


def scan_lookup(df: DataFrame, key: str, value) -> DataFrame:
    """A full scan: the predicate is wrapped so that no statistic can skip rows. rows_read, found."""
    hit = F.concat(F.col(key).cast("string"), F.lit("")) == str(value)
    return df.agg(F.count("*").alias("rows_read"), F.count_if(hit).alias("found"))


def guess_numbers(spark: SparkSession, low: int, high: int, targets: DataFrame | None = None) -> DataFrame:
    """(target, guesses): halving search for every number of low..high, one guess per recursion level. targets (one column of distinct numbers within low..high): for these only."""
    if targets is None:
        targets = spark.range(low, high + 1)
    return spark.sql(
        f"""WITH RECURSIVE g(target, lo, hi, guesses, done) AS (
          SELECT target, {int(low)}L, {int(high)}L, 0, false FROM {{targets}}
          UNION ALL
          SELECT target, IF((lo + hi) DIV 2 < target, (lo + hi) DIV 2 + 1, lo), IF((lo + hi) DIV 2 > target, (lo + hi) DIV 2 - 1, hi), guesses + 1, (lo + hi) DIV 2 = target FROM g WHERE NOT done)
        SELECT target, guesses FROM g WHERE done""",
        targets=targets.toDF("target"),
    )


def guess_numbers_linear(spark: SparkSession, low: int, high: int, targets: DataFrame | None = None) -> DataFrame:
    """As `guess_numbers`, counting up from the least number."""
    targets = (spark.range(low, high + 1) if targets is None else targets).toDF("target")
    return targets.select("target", (F.col("target") - low + 1).cast("int").alias("guesses"))


def bisect_lookup(spark: SparkSession, values: DataFrame, column: str, value) -> DataFrame:
    """(value, guesses) of one value in a ranked table (`column`, key 0..n-1); no row if it is absent. One probe per level."""
    n = values.count()
    kind = values.schema[column].dataType.simpleString()
    return spark.sql(
        f"""WITH RECURSIVE g(lo, hi, guesses, found) AS (
          SELECT 0L, {n - 1}L, 0, CAST(NULL AS {kind})
          UNION ALL
          SELECT IF(s.v < :value, s.key + 1, g.lo), IF(s.v > :value, s.key - 1, g.hi), g.guesses + 1, IF(s.v = :value, s.v, NULL)
          FROM g JOIN {{ranked}} s ON s.key = (g.lo + g.hi) DIV 2 WHERE g.found IS NULL AND g.lo <= g.hi)
        SELECT found AS value, guesses FROM g WHERE found IS NOT NULL""",
        {"value": value},
        ranked=values.select(F.col(column).alias("v"), "key"),
    )


def matrix_walk(graph: PropertyGraph, spark: SparkSession, moves: list[tuple[str, str]], ids: list[int], clear_start_after: int | None = None) -> DataFrame:
    """(pos, weight): a row vector times one sparse adjacency slice per (label, direction).

    clear_start_after: after that many products the start's own entries are set to zero, as the element filter does.
    """
    x = spark.createDataFrame([(int(i),) for i in ids], "col long").groupBy("col").agg(F.count("*").alias("val"))
    for n, (label, direction) in enumerate(moves, 1):
        e = graph.edges(label)
        m = e.groupBy(F.col("src" if direction == "out" else "dst").alias("row"), F.col("dst" if direction == "out" else "src").alias("to")).agg(F.count("*").alias("m"))
        x = x.join(m, x.col == m.row).groupBy(F.col("to").alias("col")).agg(F.sum(F.col("val") * F.col("m")).alias("val"))
        if n == clear_start_after:
            x = x.where(~F.col("col").isin(*ids))
    return x.select(F.col("col").alias("pos"), F.col("val").alias("weight"))


def flat_lookup(df: DataFrame, key: str, value) -> DataFrame:
    """A key/value collection: one partition holds the item; no edge ever leaves it."""
    return df.where(F.col(key) == value)
