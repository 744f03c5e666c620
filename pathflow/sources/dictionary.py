"""Dense integer keys for strings, without a lossy hash and without one task that sees everything."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .scratch import stored


def global_rank(rows: DataFrame, order: list, name: str, tag: str = "rank") -> DataFrame:
    """`rows` with the 0-based rank by the sort expressions `order`, which must tell all rows apart.

    Range partitions are numbered as they are written, by their number and the row's place in it; their counts (one row per partition) give the offsets.
    """
    ranged = stored(rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()), tag)
    part, rank = F.shiftright("_at", 33), F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    counts = ranged.groupBy(part.alias("_p")).count()
    before = W.orderBy("_p").rowsBetween(W.unboundedPreceding, -1)
    starts = counts.select("_p", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("_start"))
    joined = ranged.join(F.broadcast(starts), part == F.col("_p"))  # one row per partition
    return joined.withColumn(name, (rank + F.col("_start")).cast("long")).drop("_at", "_p", "_start")


def dictionary(values: DataFrame, column: str, tag: str = "dictionary") -> DataFrame:
    """(column, key): key is the 0-based rank of the distinct non-null value."""
    distinct = values.select(column).where(F.col(column).isNotNull()).distinct()
    return global_rank(distinct, [F.col(column)], "key", tag)
