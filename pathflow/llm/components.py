"""Connected components of an edge table: hook every vertex on its least neighbour, then jump pointers.

Nothing but row counts reaches the driver. Each round ends in a table in the shared folder, so that
lineage stays short and lost executors cost one step. Rounds grow with the logarithm of the vertices.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize


def _canonical(edges: DataFrame) -> DataFrame:
    return edges.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()


def _flatten(parent: DataFrame) -> DataFrame:
    """parent(node, root) with root < node: jump until every root is a root."""
    while True:
        up = parent.select(F.col("node").alias("r"), F.col("root").alias("top"))
        jumped = materialize(
            parent.join(up, parent.root == up.r, "left").select("node", F.coalesce("top", "root").alias("root"), F.col("top").isNotNull().alias("moved")), "jump"
        )
        discard(parent)
        parent = jumped
        if jumped.where("moved").isEmpty():
            return parent


def relabel(frame: DataFrame, column: str, labels: DataFrame) -> DataFrame:
    """Replace `column` by its root where `labels` (node, root) has one."""
    to = labels.select(F.col("node").alias("_node"), F.col("root").alias("_root"))
    return frame.join(to, F.col(column) == F.col("_node"), "left").withColumn(column, F.coalesce("_root", column)).drop("_node", "_root")


def connected_components(edges: DataFrame) -> DataFrame | None:
    """edges (u, v) -> table (node, root) of all vertices that are not the least of their component.

    None if there is no edge between two different vertices. Loops, repeats and null ends are ignored.
    """
    left = materialize(_canonical(edges), "edges")
    labels = None
    while not left.isEmpty():
        parent = _flatten(materialize(left.groupBy(F.col("v").alias("node")).agg(F.min("u").alias("root")), "hook"))
        step = parent.select("node", "root")
        if labels is None:
            labels, old = parent, None
        else:
            old, labels = labels, materialize(relabel(labels.select("node", "root"), "root", step).unionByName(step), "labels")
        rest = materialize(_canonical(relabel(relabel(left, "u", step), "v", step)), "edges")
        discard(left, old, parent if labels is not parent else None)
        left = rest
    discard(left)
    return labels
