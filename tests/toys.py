"""Hand-made toy graphs; they satisfy every statement made about the worked examples."""

from pyspark.sql import functions as F

from pathflow.functions.regions import BOX
from pathflow.operators.region_tree import tree_of
from pathflow.sources.graph import EdgeLabel, PropertyGraph, VertexClass


def graph(spark, edges, names=None):
    """edges: {label: [(src, dst), ...]} over plain ids."""
    classes = []
    if names:
        rows = spark.createDataFrame(list(names.items()), "vid long, name string")
        classes = [VertexClass("person", 1, lambda: rows, ("name",))]
    labels = []
    for label, pairs in edges.items():
        df = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(pairs)], "eid long, src long, dst long")
        labels.append(EdgeLabel(label, lambda df=df: df))
    return PropertyGraph.of(classes, labels)


def friends(spark):
    return graph(spark, {"friend": [(1, 2), (1, 3), (1, 4)], "kin": [(1, 5), (2, 3)]}, {1: "Ada", 2: "Bo", 3: "Cy", 4: "Di", 5: "Ed"})


def taste(spark):
    return graph(spark, {"likes": [(7, 3), (7, 4), (1, 3), (1, 2), (1, 5)], "feature": [(3, 8), (2, 8), (4, 6), (5, 6)]})


QUADS = {1: (0, 0, 100, 100), 2: (0, 0, 40, 100), 3: (40, 0, 70, 100), 4: (70, 0, 100, 100), 5: (0, 50, 40, 100), 6: (0, 0, 40, 50), 7: (40, 50, 70, 100), 8: (70, 0, 100, 50), 9: (42, 22, 68, 44)}
SUB = {2: 1, 3: 1, 4: 1, 5: 2, 6: 2, 7: 3, 9: 3, 8: 4}
#: a to i as 11 to 19
POIS = {
    11: (5, (5, 80, 7, 82)), 12: (5, (20, 60, 22, 62)), 13: (6, (30, 30, 32, 32)), 14: (9, (50, 30, 52, 32)), 15: (7, (45, 90, 47, 92)), 16: (7, (60, 70, 62, 72)),
    17: (7, (50, 55, 52, 57)), 18: (8, (80, 40, 82, 42)), 19: (8, (95, 10, 97, 12)),
}
RECT = (25, 20, 90, 45)


def region(spark):
    box = ", ".join(f"{c} double" for c in BOX)
    quads = spark.createDataFrame([(q, *map(float, b)) for q, b in QUADS.items()], f"quad long, {box}")
    sub = spark.createDataFrame(list((p, q) for q, p in SUB.items()), "parent long, quad long")
    pois = spark.createDataFrame([(p, q, *map(float, b)) for p, (q, b) in POIS.items()], f"poi long, quad long, {box}")
    return tree_of(quads, sub, pois)


def bag(df, key="pos"):
    """{position: weight} of a result."""
    return {r[0]: r[1] for r in df.select(F.col(key), "weight").collect()}
