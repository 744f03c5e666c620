"""Reductions of a walk's result: counts are weighted, as a frontier is a multiset."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graph import PropertyGraph


def count(frontier: DataFrame) -> DataFrame:
    """One row: traversers (with repeats) and distinct places."""
    return frontier.agg(F.coalesce(F.sum("weight"), F.lit(0)).alias("traversers"), F.count("*").alias("places"))


def exists(frontier: DataFrame) -> bool:
    return not frontier.isEmpty()


def limit(frontier: DataFrame, n: int) -> DataFrame:
    """The n places with the least ids."""
    return frontier.orderBy("pos").limit(n)


def group_count(graph: PropertyGraph, frontier: DataFrame, key: str) -> DataFrame:
    """(value, times) of a property over the frontier; places without it are left out."""
    p = graph.with_property(key)
    return frontier.join(p, frontier.pos == p.vid).where("value IS NOT NULL").groupBy("value").agg(F.sum("weight").alias("times"))


def weighted_mean(graph: PropertyGraph, frontier: DataFrame, key: str) -> DataFrame:
    p = graph.with_property(key)
    return frontier.join(p, frontier.pos == p.vid).agg((F.sum(F.col("value") * F.col("weight")) / F.sum(F.when(F.col("value").isNotNull(), F.col("weight")))).alias("mean"))
