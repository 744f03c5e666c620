"""Readers and writers: tables, edge lists in several formats, links of pages, JSON properties."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "src BIGINT, dst BIGINT"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    """Edges (src, dst) from csv, json, orc, parquet or blank-separated text."""
    if fmt == "text":
        parts = F.split("value", " ")
        return spark.read.text(path).select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"))
    return spark.read.schema(EDGE_SCHEMA).format(fmt).load(path)


def write_result(df: DataFrame, path: str, fmt: str, mode: str = "errorifexists") -> None:
    if fmt == "text":
        df = df.select(F.concat_ws(" ", *df.columns).alias("value"))
    df.write.format(fmt).mode(mode).save(path)


def html_links(pages: DataFrame) -> DataFrame:
    """(page, href): one row per link of a page, repeats kept."""
    links = F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1)
    return pages.select(F.col("page_id").alias("page"), F.explode(links).alias("href"))


def json_property(column: str, key: str, kind: str) -> Column:
    """A typed property of a JSON text; null if it is missing or of another kind."""
    return F.try_variant_get(F.try_parse_json(column), f"$.{key}", kind)
