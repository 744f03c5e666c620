"""The property graph over tables: vertex classes and edge labels, declared once.

Vertex ids are `code * 2^56 + key`: injective, sortable, and the class is the upper byte. Edges carry an id, so parallel edges count.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

KEY_BITS = 56


class UnknownLabel(ValueError): ...


class UnknownKey(ValueError): ...


class UnknownClass(ValueError): ...


def vid(code: int, key: Column) -> Column:
    return key.cast("long") + F.lit(code << KEY_BITS)


def key_of(position: Column) -> Column:
    return position.bitwiseAND(F.lit((1 << KEY_BITS) - 1))


@dataclass(frozen=True)
class VertexClass:
    """rows() gives one row per vertex: `vid` and one typed column per property; a missing property is null."""

    name: str
    code: int
    rows: Callable[[], DataFrame]
    keys: tuple[str, ...] = ()


@dataclass(frozen=True)
class EdgeLabel:
    """rows() gives `eid, src, dst` (vertex ids) and typed property columns. tree: every vertex has one incoming edge of it."""

    name: str
    rows: Callable[[], DataFrame]
    keys: tuple[str, ...] = ()
    tree: bool = False
    weight: str | None = None  # a property that multiplies the walker's weight (virtual edges)
    by_head: Callable[[], DataFrame] | None = None  # a second copy, clustered by dst


@dataclass
class PropertyGraph:
    classes: dict[str, VertexClass] = field(default_factory=dict)
    labels: dict[str, EdgeLabel] = field(default_factory=dict)
    virtual: dict[tuple, str] = field(default_factory=dict)  # steps of a walk -> label of its materialised edge

    @classmethod
    def of(cls, classes: list[VertexClass], labels: list[EdgeLabel]) -> PropertyGraph:
        return cls({c.name: c for c in classes}, {x.name: x for x in labels})

    def vertices(self, name: str) -> DataFrame:
        if name not in self.classes:
            raise UnknownClass(name)
        return self.classes[name].rows()

    def edges(self, *names: str, into: bool = False) -> DataFrame:
        """Edges of the labels: eid, label, src, dst and their properties as p_<key>; all labels if none is named. into: the copy by head."""
        out = None
        for name in names or tuple(self.labels):
            if name not in self.labels:
                raise UnknownLabel(name)
            x = self.labels[name]
            props = [F.col(k).alias(f"p_{k}") for k in x.keys]
            rows = x.by_head if into and x.by_head else x.rows
            one = rows().select("eid", F.lit(name).alias("label"), "src", "dst", *props)
            out = one if out is None else out.unionByName(one, allowMissingColumns=True)
        return out

    def with_property(self, key: str) -> DataFrame:
        """(vid, value) of every class that has the property."""
        found = [c for c in self.classes.values() if key in c.keys]
        if not found:
            raise UnknownKey(key)
        out = None
        for c in found:
            one = c.rows().select("vid", F.col(key).alias("value"))
            out = one if out is None else out.unionByName(one)
        return out

    def with_properties(self, needed: list[str], wanted: list[str]) -> DataFrame:
        """vid and p_<key> of the wanted keys (null where a class lacks one), of every class that has all needed keys."""
        for key in {*needed, *wanted}:
            if not any(key in c.keys for c in self.classes.values()):
                raise UnknownKey(key)
        out = None
        for c in self.classes.values():
            if set(needed) <= set(c.keys):
                one = c.rows().select("vid", *[F.col(k).alias(f"p_{k}") for k in dict.fromkeys(wanted) if k in c.keys])
                out = one if out is None else out.unionByName(one, allowMissingColumns=True)
        if out is None:  # no class has them all
            c = next(iter(self.classes.values()))
            return c.rows().limit(0).select("vid", *[F.lit(None).alias(f"p_{k}") for k in dict.fromkeys(wanted)])
        return out.select("vid", *[F.col(f"p_{k}") if f"p_{k}" in out.columns else F.lit(None).alias(f"p_{k}") for k in dict.fromkeys(wanted)])

    def single(self, label: str) -> PropertyGraph:
        """The single-relational graph of one label."""
        if label not in self.labels:
            raise UnknownLabel(label)
        return PropertyGraph(dict(self.classes), {label: self.labels[label]})

    def subgraph(self, label: str, predicate: Callable[[DataFrame], Column]) -> PropertyGraph:
        """The same graph with the edges of one label filtered, lazily."""
        old = self.labels[label]
        kept = EdgeLabel(label, lambda: (lambda df: df.where(predicate(df)))(old.rows()), old.keys, old.tree, old.weight)
        return PropertyGraph(dict(self.classes), self.labels | {label: kept}, dict(self.virtual))

    def reverse(self) -> PropertyGraph:
        def turned(x: EdgeLabel) -> EdgeLabel:
            return EdgeLabel(x.name, lambda: x.rows().select("eid", F.col("dst").alias("src"), F.col("src").alias("dst"), *x.keys), x.keys, False, x.weight)

        return PropertyGraph(dict(self.classes), {n: turned(x) for n, x in self.labels.items()})

    def union(self, other: PropertyGraph) -> PropertyGraph:
        clash = set(self.labels) & set(other.labels)
        if clash:
            raise ValueError(f"labels in both graphs: {sorted(clash)}")
        return PropertyGraph(self.classes | other.classes, self.labels | other.labels, self.virtual | other.virtual)

    def generic_vertices(self) -> DataFrame:
        """(vid, vclass, props VARIANT): the dynamic view of all classes."""
        out = None
        for c in self.classes.values():
            props = F.to_variant_object(F.struct(*[F.col(k) for k in c.keys])) if c.keys else F.parse_json(F.lit("{}"))
            one = c.rows().select("vid", F.lit(c.name).alias("vclass"), props.alias("props"))
            out = one if out is None else out.unionByName(one)
        return out

    def validate(self) -> DataFrame:
        """(label, check, n): dangling ends and repeated edge ids of every label."""
        every = None
        for c in self.classes.values():
            ids = c.rows().select("vid")
            every = ids if every is None else every.unionByName(ids)
        every = every.distinct()
        out = None
        for name, x in self.labels.items():
            e = x.rows().select("eid", "src", "dst")
            checks = [
                (f"dangling_{side}", e.join(every, e[side] == every.vid, "left_anti").agg(F.count("*").alias("n"))) for side in ("src", "dst")
            ] + [("repeated_eid", e.groupBy("eid").count().where("count > 1").agg(F.count("*").alias("n")))]
            for check, df in checks:
                one = df.select(F.lit(name).alias("label"), F.lit(check).alias("check"), "n")
                out = one if out is None else out.unionByName(one)
        return out

    def degrees(self, label: str, direction: str = "out") -> DataFrame:
        """(vid, degree), parallel edges counted."""
        side = {"out": "src", "in": "dst"}[direction]
        return self.labels[label].rows().groupBy(F.col(side).alias("vid")).agg(F.count("*").alias("degree"))

    def write_layout(self, path: str, buckets: int = 64) -> None:
        """Two copies of the edges, by tail and by head: partitioned by label, clustered and sorted on the walked end.

        A literal start then reads only the files and row groups whose min/max hold it, and a label only its own folder.
        """
        edges = self.edges().select("eid", "label", "src", "dst")
        for side in ("src", "dst"):
            dealt = edges.repartitionByRange(buckets, "label", side).sortWithinPartitions("label", side)
            dealt.write.partitionBy("label").parquet(f"{path}/by_{side}")

    @classmethod
    def from_layout(cls, spark: SparkSession, path: str, labels: list[str], classes: list[VertexClass] | None = None) -> PropertyGraph:
        """The graph of a folder that `write_layout` made: hops out read the copy by tail, hops in the copy by head."""

        def copy(side: str, label: str) -> Callable[[], DataFrame]:
            return lambda: spark.read.parquet(f"{path}/by_{side}").where(F.col("label") == label).drop("label")

        return cls.of(classes or [], [EdgeLabel(x, copy("src", x), by_head=copy("dst", x)) for x in labels])
