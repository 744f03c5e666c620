"""K-d tree sharding: split at weighted medians along the widest metadata dimension until leaves reach the target.

Only DataFrame functions run on the executors. The tree lives on the driver: at most 2 * shards - 1 nodes. For each level
one aggregate finds every node's widest dimension; then a few aggregates narrow each node's weighted median: sizes are summed into
1024 buckets of the node's current key interval, and only the bucket with the median is refined. What is collected is bounded by
nodes * 1024 rows whatever the data. A key is the dimension's value, scaled to 20 bits, above 43 bits of a
hash, so that a value that a third of all rows share still splits at the right weight.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import discard, materialize

TIE_BITS, VALUE_BITS, BUCKET_BITS = 43, 20, 10


@dataclass
class Node:
    leaves: int
    first: int  # shard of its first leaf
    dim: int = -1
    cut: int = 0
    low: Node | None = None
    high: Node | None = None

    def shard(self, keys: list[Column]) -> Column:
        """The declarative form of the tree: nested CASE WHEN over the keys."""
        if self.low is None:
            return F.lit(self.first)
        return F.when(keys[self.dim] < self.cut, self.low.shard(keys)).otherwise(self.high.shard(keys))


def text_value(col: Column) -> Column:
    """Order-preserving number of a string's first 6 UTF-8 bytes; null: 0."""
    head = F.rpad(F.hex(F.coalesce(col, F.lit("")).cast("binary")).substr(1, 12), 12, "0")
    return F.conv(head, 16, 10).cast("double")


def _at_node(values: dict[int, int], shards: int, kind: str = "long") -> Column:
    """The node's value: a literal array, indexed by the node; null elsewhere."""
    return F.get(F.array(*[F.lit(values.get(i)).cast(kind) for i in range(shards)]), F.col("_node"))


def kd_shards(rows: DataFrame, dims: list[str], size: str, tie: Column, shards: int) -> tuple[Node, DataFrame]:
    """The fitted tree, and `rows` with the column `shard` (replaced if there is one) instead of `dims`, as a table in the shared folder.

    Leaves take total * 1 / shards of the size each, as near as one row allows: a node of k leaves is cut at the weight
    floor(k/2)/k of its own. Null values stand at the low end; null sizes weigh nothing. Rows with equal keys (repeats) stay together. An empty table gives
    a tree of one leaf. Long texts are only carried. Other columns may have any name.
    """
    ends = rows.agg(F.count("*").alias("n"), *[F.min(d).alias(f"lo_{d}") for d in dims], *[F.max(d).alias(f"hi_{d}") for d in dims]).first()
    hashed = F.shiftrightunsigned(tie, 64 - TIE_BITS)
    kept = [c for c in rows.columns if c not in dims and c != "shard"]
    keys = []
    for i, d in enumerate(dims):
        lo, span = ends[f"lo_{d}"], (ends[f"hi_{d}"] or 0) - (ends[f"lo_{d}"] or 0)
        scaled = F.floor((F.col(d) - lo) / span * (2**VALUE_BITS - 1)) if span else F.lit(0)
        keys.append(F.shiftleft(F.coalesce(scaled.cast("long"), F.lit(0).cast("long")), TIE_BITS).bitwiseOR(hashed).alias(f"_k{i}"))
    at = materialize(rows.select(F.struct(*kept).alias("_row"), F.coalesce(F.col(size), F.lit(0)).alias("_size"), F.lit(0).alias("_node"), *keys), "kd")
    size = "_size"
    root = Node(shards if ends["n"] else 1, 0)
    level = [root]
    while open_nodes := {n.first: n for n in level if n.leaves > 1}:
        ks = [F.col(f"_k{i}") for i in range(len(dims))]
        ends = at.groupBy("_node").agg(F.sum(size).alias("w"), *[F.min(k).alias(f"lo{i}") for i, k in enumerate(ks)], *[F.max(k).alias(f"hi{i}") for i, k in enumerate(ks)])
        goal, low, high = {}, {}, {}  # the cut lies in low..high
        for n in open_nodes.values():
            n.dim, low[n.first] = 0, 0
        for r in ends.collect():
            if n := open_nodes.get(r["_node"]):
                n.dim = max(range(len(dims)), key=lambda i: (r[f"hi{i}"] >> TIE_BITS) - (r[f"lo{i}"] >> TIE_BITS))
                goal[n.first] = r["w"] * (n.leaves // 2) / n.leaves
                low[n.first], high[n.first] = r[f"lo{n.dim}"], r[f"hi{n.dim}"]
        key = F.get(F.array(*ks), _at_node({i: n.dim for i, n in open_nodes.items()}, shards, "int"))
        done = {i: 0.0 for i in goal}  # weight below `low`
        todo = set(goal)
        while todo:
            shift = {i: max(0, (high[i] - low[i]).bit_length() - BUCKET_BITS) for i in todo}
            inside = key.between(_at_node({i: low[i] for i in todo}, shards), _at_node({i: high[i] for i in todo}, shards))
            offset = F.call_function("shiftright", key - _at_node({i: low[i] for i in todo}, shards), _at_node(shift, shards, "int"))
            # rows outside their node's interval count as bucket null; at most 1025 rows a node come back
            hist = at.withColumn("_k", key).groupBy("_node", F.when(inside, offset).alias("_b")).agg(F.sum(size).alias("w"), F.min("_k").alias("lo"), F.max("_k").alias("hi"))
            sums: dict[int, list] = {}
            for r in hist.collect():
                if r["_b"] is not None and r["_node"] in todo:
                    sums.setdefault(r["_node"], []).append((r["_b"], r["w"], r["lo"], r["hi"]))
            for i in list(todo):
                for _, w, first, last in sorted(sums[i]):
                    if done[i] + w >= goal[i]:
                        low[i], high[i] = first, last
                        if first == last:  # one row, or rows with one key: the nearer side
                            low[i] += done[i] + w - goal[i] <= goal[i] - done[i]
                            todo.discard(i)
                        break
                    done[i] += w
                else:
                    low[i] = high[i] + 1
                    todo.discard(i)
        for i, n in open_nodes.items():
            half = n.leaves // 2
            n.cut, n.low, n.high = low[i], Node(half, n.first), Node(n.leaves - half, n.first + half)
        upper = _at_node({i: n.high.first for i, n in open_nodes.items()}, shards, "int")
        moved = F.when(key >= _at_node(low, shards), upper).otherwise(F.col("_node"))
        split = materialize(at.withColumn("_node", moved), "kd")
        discard(at)
        at, level = split, [c for n in open_nodes.values() for c in (n.low, n.high)]
    return root, at.select("_row.*", F.col("_node").alias("shard"))


def number_slots(rows: DataFrame, shard: str, order: list[str], rows_a_bucket: int = 50_000) -> DataFrame:
    """`slot`: 0, 1, 2, ... within each shard, numbered in hash buckets so that no task sorts a whole shard."""
    n = rows.groupBy(shard).count().agg(F.max("count")).first()[0] or 0
    buckets = 1 << max(4, (n // rows_a_bucket).bit_length())
    keys = [f"o{i}" for i in range(len(order))]
    dealt = rows.select(F.struct(*[c for c in rows.columns if c != "slot"]).alias("row"), F.col(shard).alias("s"), *[F.col(c).alias(k) for c, k in zip(order, keys, strict=True)])
    dealt = dealt.withColumn("b", F.pmod(F.xxhash64(*keys), F.lit(buckets)).cast("int"))
    counts = dealt.groupBy("s", "b").count()
    before = W.partitionBy("s").orderBy("b").rowsBetween(W.unboundedPreceding, -1)
    starts = counts.select("s", "b", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first"))
    inside = F.row_number().over(W.partitionBy("s", "b").orderBy(*keys))
    joined = dealt.withColumn("n", inside).join(starts, ["s", "b"])
    return joined.select("row.*", (F.col("first") + F.col("n") - 1).cast("long").alias("slot"))
