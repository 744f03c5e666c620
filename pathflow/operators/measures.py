"""Cost measures: micro-operation formulas, degrees, cut ratio, chains."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def relational_cost(n: Column, x: Column, k: Column) -> dict[str, Column]:
    """The six micro-operations of the join plan: name probe, id read, friend probe, id reads, row probes, name reads."""
    log = lambda c: F.log2(F.greatest(c.cast("double"), F.lit(1.0)))
    return {"term1": log(n), "term2": F.lit(1.0), "term3": log(x), "term4": k.cast("double"), "term5": k * log(n), "term6": k.cast("double")}


def walk_cost(n: Column, k: Column, x: Column, y: int) -> dict[str, Column]:
    """The four micro-operations of the walk: name probe, edges read (k friends among k + x), heads, property cells."""
    return {"term1": F.log2(F.greatest(n.cast("double"), F.lit(1.0))), "term2": (k + x).cast("double"), "term3": k.cast("double"), "term4": (k * y).cast("double")}


def with_total(df: DataFrame, terms: dict[str, Column], digits: int = 6) -> DataFrame:
    total = sum(terms.values(), F.lit(0.0))
    return df.select("*", *[F.round(c, digits).alias(name) for name, c in terms.items()], F.round(total, digits).alias("total"))


def degree_profile(edges: DataFrame, label: str) -> DataFrame:
    """label, vertices, edges, greatest, median and mean out-degree, and the vertex of the greatest (the least of them on a tie)."""
    d = edges.groupBy("src").agg(F.count("*").alias("d"))
    return d.agg(
        F.count("*").alias("vertices"), F.sum("d").alias("edges"), F.max("d").alias("max_degree"), F.percentile("d", F.lit(0.5)).alias("median_degree"), F.round(F.avg("d"), 6).alias("mean_degree"), F.max_by("src", F.struct("d", -F.col("src"))).alias("max_vertex")
    ).select(F.lit(label).alias("label"), "*")


def cut_ratio(edges: DataFrame, parts: int, label: str) -> DataFrame:
    """Edges whose ends fall into different parts when vertices are dealt by key modulo `parts`."""
    cut = F.count_if(F.pmod("src", F.lit(parts)) != F.pmod("dst", F.lit(parts)))
    return edges.agg(cut.alias("cut"), F.count("*").alias("total")).select(F.lit(label).alias("label"), "cut", "total")


def index_space(rows: DataFrame, nodes: DataFrame) -> DataFrame:
    """(rows, nodes): the original and its index structure, counted."""
    return rows.agg(F.count("*").alias("rows")).crossJoin(F.broadcast(nodes.agg(F.count("*").alias("nodes"))))
