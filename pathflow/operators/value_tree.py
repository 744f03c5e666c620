"""A search tree over a property's distinct values, as vertices and `sub` edges of the graph."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.lower import run
from ..plans.traversal import HERE, Walk
from ..sources.dictionary import dictionary
from ..sources.graph import EdgeLabel, PropertyGraph, VertexClass, vid
from ..sources.scratch import stored

NODE = 22


class ValueTree:
    """Nodes of level l hold fanout^(l+1) consecutive distinct values; leaves of the walk are the data vertices.

    data: (key, value) of one vertex class with class code `code`. Null values are not indexed. Levels = ceil(log_fanout n), at least 1.
    """

    def __init__(self, data: DataFrame, code: int, fanout: int = 16):
        if fanout < 2:
            raise ValueError("fanout must be 2 or more")
        ranks = stored(dictionary(data, "value", "value-ranks"), "value-ranks")
        n = ranks.count()
        levels = 1
        while fanout**levels < n:
            levels += 1
        self.levels, self.fanout, self.code = levels, fanout, code
        each = ranks.select("value", "key", F.explode(F.sequence(F.lit(0), F.lit(levels - 1))).alias("level"))
        size = F.pow(F.lit(float(fanout)), F.col("level") + 1).cast("long")
        place = F.floor(F.col("key") / size).cast("long")
        node = F.shiftleft(F.col("level").cast("long"), 40).bitwiseOR(F.col("place"))
        nodes = each.withColumn("place", place).groupBy("level", "place").agg(F.min("value").alias("lo"), F.max("value").alias("hi")).withColumn("node", node)
        self.nodes = stored(nodes, "value-tree")
        self.ranks, self.data = ranks, data

    def as_graph(self) -> PropertyGraph:
        def vertices() -> DataFrame:
            tree = self.nodes.select(vid(NODE, F.col("node")).alias("vid"), "lo", "hi")
            return tree.unionByName(self.data.where("value IS NOT NULL").select(vid(self.code, F.col("key")).alias("vid"), F.col("value").alias("lo"), F.col("value").alias("hi")))

        return PropertyGraph.of([VertexClass("entry", NODE, vertices, ("lo", "hi"))], [EdgeLabel("sub", lambda: self.sub, ("lo", "hi"), tree=True)])

    @cached_property
    def sub(self) -> DataFrame:
        """Edges from a node to its children, clustered by node, with the range of the child: a round of the descent meets this table alone."""
        up = F.shiftleft((F.col("level") + 1).cast("long"), 40).bitwiseOR(F.floor(F.col("place") / self.fanout).cast("long"))
        inner = self.nodes.where(F.col("level") < self.levels - 1).select(vid(NODE, up).alias("src"), vid(NODE, F.col("node")).alias("dst"), "lo", "hi")
        leaf = self.ranks.select("value", F.floor(F.col("key") / self.fanout).cast("long").alias("leaf"))
        data = self.data.join(leaf, "value").select(vid(NODE, F.col("leaf")).alias("src"), vid(self.code, F.col("key")).alias("dst"), F.col("value").alias("lo"), F.col("value").alias("hi"))
        edges = inner.unionByName(data).withColumn("eid", F.col("dst"))
        return stored(edges.repartitionByRange("src").sortWithinPartitions("src"), "value-sub")

    @property
    def root(self) -> int:
        return (NODE << 56) + ((self.levels - 1) << 40)

    def descent(self, lo, hi) -> Walk:
        """One round: children whose range meets lo..hi."""
        return HERE.out_edges("sub").keep("lo", "<=", hi).keep("hi", ">=", lo).head()

    def range(self, spark: SparkSession, lo, hi) -> DataFrame:
        """Data vertices with lo <= value <= hi: exactly levels + 1 rounds; the tree is even."""
        walk = HERE
        for _ in range(self.levels):
            walk = walk >> self.descent(lo, hi)
        return run(self.as_graph(), spark, walk, [self.root])

    def lookup(self, spark: SparkSession, value) -> DataFrame:
        return self.range(spark, value, value)
