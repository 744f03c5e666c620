"""Lowering: a walk and a start become one lazy DataFrame.

A frontier is (origin?, marks, position, weight). Every step is linear in the weights, so equal positions merge with the sum of
their weights after each hop that may repeat them ("bulking"); tree edges cannot repeat a position and skip it. Marks stop being
grouping columns after their last use.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.predicates import compare
from ..sources.dictionary import global_rank
from ..sources.graph import PropertyGraph, UnknownKey
from ..sources.scratch import stored
from .rewrite import optimize
from .traversal import BindError, Step, Walk, kind_after, marks_used

#: Literal starts up to this many ids become an IN list on the edge scan.
IN_LIST = 10_000


@dataclass(frozen=True)
class Frontier:
    df: DataFrame
    kind: str = "V"
    keys: tuple[str, ...] = ()  # origin and live marks
    mode: str = "bulk"  # bulk, rows or paths
    literal: tuple[int, ...] | None = None  # the ids, while they are known on the driver
    fresh: bool = True  # no position repeats within its keys

    @property
    def position(self) -> str:
        return {"V": "pos", "E": "eid", "S": "value"}[self.kind]


@dataclass
class Lowering:
    graph: PropertyGraph
    spark: SparkSession
    trace: list = field(default_factory=list)  # (step number, text, frontier) if asked for
    tracing: bool = False
    after: frozenset[str] = frozenset()  # marks that are compared with after the step at hand

    def start(self, ids=None, frame: DataFrame | None = None, per_origin: bool = False, mode: str = "bulk") -> Frontier:
        """ids: vertex ids, repeats count. frame: a DataFrame with `pos` and maybe `weight`, or (origin, pos)."""
        literal = None
        if frame is None:
            ids = list(ids)
            frame = self.spark.createDataFrame([(int(i),) for i in ids], "pos long")
            literal = tuple(dict.fromkeys(int(i) for i in ids)) if len(ids) <= IN_LIST else None
        if "weight" not in frame.columns:
            frame = frame.withColumn("weight", F.lit(1).cast("long"))
        keys = ()
        if per_origin or "origin" in frame.columns:
            if "origin" not in frame.columns:
                frame = frame.withColumn("origin", F.col("pos"))
            keys = ("origin",)
        frame = frame.select(*keys, "pos", "weight")
        if mode == "paths":
            frame = frame.withColumn("path", F.array(F.struct(F.lit("V").alias("kind"), F.col("pos").alias("id"))))
        f = Frontier(frame, "V", keys, mode, literal, False)
        return self.bulk(f) if mode == "bulk" else f

    # -- multiset forms
    def bulk(self, f: Frontier) -> Frontier:
        if f.mode != "bulk" or f.fresh:
            return f
        by = [*f.keys, f.position]
        if f.kind == "E":
            return f
        return replace(f, df=f.df.groupBy(*by).agg(F.sum("weight").alias("weight")), fresh=True)

    def run(self, walk: Walk, f: Frontier, live: frozenset[str] = frozenset()) -> Frontier:
        """live: marks that are compared with after this walk."""
        steps = walk.steps
        for i, s in enumerate(steps):
            later = marks_used(steps[i:]) | live
            f = self._forget(f, {k for k in f.keys if k.startswith("m_") and k[2:] not in later and not (s.op == "mark" and k == f"m_{s.args[0]}")})
            self.after = frozenset(marks_used(steps[i + 1 :]) | live)
            before, f = f, getattr(self, f"_{s.op}")(f, s)
            if self.tracing:
                if s.op == "end":  # later steps and their counters begin at this table, not at the start of the walk
                    f = replace(f, df=stored(f.df, "touched"))
                self.trace.append((len(self.trace), s, before, f))
        return f

    def _forget(self, f: Frontier, dead: set[str]) -> Frontier:
        if not dead:
            return f
        f = replace(f, df=f.df.drop(*dead), keys=tuple(k for k in f.keys if k not in dead), fresh=False)
        return f if f.kind == "E" else self.bulk(f)

    def _run_arm(self, f: Frontier, walk: Walk, after: frozenset[str]) -> Frontier:
        """A walk from f whose own marks end with it: keys are those of f that are still needed, columns those that all arms share."""
        end = self.run(walk, f, after)
        keys = tuple(k for k in f.keys if k == "origin" or k[2:] in after)
        end = self._forget(end, {k for k in end.keys if k not in keys})
        extra = ["path"] if end.mode == "paths" else []
        if end.kind == "E":
            return end
        return self.bulk(replace(end, df=end.df.select(*keys, end.position, "weight", *extra), keys=keys))

    # -- steps
    def _edges(self, f: Frontier, s: Step) -> Frontier:
        direction, labels = s.args
        sides = {"out": ("src", "dst"), "in": ("dst", "src")}
        parts = []
        for d in ("out", "in") if direction == "both" else (direction,):
            near, far = sides[d]
            e = self.graph.edges().limit(0) if labels == ("",) else self.graph.edges(*labels, into=d == "in")
            here = e.where(F.col(near).isin(*f.literal)) if f.literal else e
            if direction == "both" and d == "in":  # a loop is met once
                here = here.where("src <> dst")
            kept = f.df.withColumnRenamed("pos", "_at")
            j = kept.join(here, F.col("_at") == F.col(near)).withColumn("far", F.col(far)).drop("_at")
            parts.append(j)
        out = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
        for name in labels or tuple(self.graph.labels):
            x = self.graph.labels.get(name)
            if x and x.weight:
                out = out.withColumn("weight", F.when(F.col("label") == name, F.col("weight") * F.col(f"p_{x.weight}")).otherwise(F.col("weight")))
        if f.mode == "paths":
            out = self._step_path(out, "E", "eid")
        tree = bool(labels) and direction == "out" and all(x in self.graph.labels and self.graph.labels[x].tree for x in labels)
        return replace(f, df=out, kind="E", literal=None, fresh=f.fresh and tree)

    def _sample_out(self, f: Frontier, s: Step) -> Frontier:
        return self._sampled(f, s, "out", "src")

    def _sample_in(self, f: Frontier, s: Step) -> Frontier:
        return self._sampled(f, s, "in", "dst")

    def _sampled(self, f: Frontier, s: Step, direction: str, near: str) -> Frontier:
        label, k, seed = s.args
        e = self._edges(f, Step("edges", (direction, (label,))))
        # md5 of edge id, keys and seed: the same choice in every engine and for every parallelism
        order = W.partitionBy(*f.keys, near).orderBy(F.md5(F.concat_ws(":", "eid", *f.keys, F.lit(seed)).cast("binary")), "eid")
        return replace(e, df=e.df.withColumn("_n", F.row_number().over(order)).where(F.col("_n") <= k).drop("_n"))

    def _end(self, f: Frontier, s: Step) -> Frontier:
        extra = ["path"] if f.mode == "paths" else []
        out = f.df.select(*f.keys, F.col(s.args[0]).alias("pos"), "weight", *extra)
        if f.mode == "paths":
            out = self._step_path(out, "V", "pos")
        return self.bulk(replace(f, df=out, kind="V"))

    @staticmethod
    def _step_path(df: DataFrame, kind: str, column: str) -> DataFrame:
        return df.withColumn("path", F.concat("path", F.array(F.struct(F.lit(kind).alias("kind"), F.col(column).alias("id")))))

    def _degree(self, f: Frontier, s: Step) -> Frontier:
        d = self.graph.degrees(*s.args)
        out = f.df.join(d, f.df.pos == d.vid).withColumn("weight", F.col("weight") * F.col("degree")).drop("vid", "degree")
        return replace(f, df=out)

    def _values(self, f: Frontier, s: Step) -> Frontier:
        (key,) = s.args
        if f.kind == "E":
            if f"p_{key}" not in f.df.columns:
                raise UnknownKey(key)
            out = f.df.withColumn("value", F.col(f"p_{key}"))
        else:
            p = self.graph.with_property(key)
            out = f.df.join(p, f.df.pos == p.vid)
        extra = ["path"] if f.mode == "paths" else []
        out = out.where(F.col("value").isNotNull()).select(*f.keys, "value", "weight", *extra)
        return self.bulk(replace(f, df=out, kind="S", fresh=False, literal=None))

    def _label(self, f: Frontier, s: Step) -> Frontier:
        keep, labels = s.args
        hit = F.col("label").isin(*labels)
        return replace(f, df=f.df.where(hit if keep else ~hit))

    def _property(self, f: Frontier, s: Step) -> Frontier:
        return self._properties(f, Step("properties", (s.args,)))

    def _properties(self, f: Frontier, s: Step) -> Frontier:
        """All filters of the step in one pass: vertices meet one table that has the keys of all of them."""
        if f.kind == "E":
            for _, key, _, _ in s.args:
                if f"p_{key}" not in f.df.columns:
                    raise UnknownKey(key)
            passes = [self._test(F.col(f"p_{key}"), keep, op, value) for keep, key, op, value in s.args]
            return replace(f, df=f.df.where(reduce(Column.__and__, passes)))
        kept = [t for t in s.args if t[0]]
        for wanted, how in ((kept, "left_semi"), ([t for t in s.args if not t[0]], "left_anti")):
            if wanted and how == "left_semi":  # a vertex that keeps must have every kept key; its dropped ones are tested in the same pass
                rows = self.graph.with_properties([t[1] for t in kept], [t[1] for t in s.args])
                hits = rows.where(reduce(Column.__and__, [self._test(F.col(f"p_{key}"), keep, op, value) for keep, key, op, value in s.args])).select("vid")
                return replace(f, df=f.df.join(hits, f.df.pos == hits.vid, how))
            for _, key, op, value in wanted:
                p = self.graph.with_property(key)
                hits = p.where(compare(F.col("value"), op, value)).select("vid")
                f = replace(f, df=f.df.join(hits, f.df.pos == hits.vid, how))
        return f

    @staticmethod
    def _test(column: Column, keep: bool, op: str, value) -> Column:
        hit = F.coalesce(compare(column, op, value), F.lit(False))
        return hit if keep else ~hit

    def _element(self, f: Frontier, s: Step) -> Frontier:
        keep, ids = s.args
        hit = F.col(f.position).isin(*ids) if ids else F.lit(False)
        return replace(f, df=f.df.where(hit if keep else ~hit))

    def _mark(self, f: Frontier, s: Step) -> Frontier:
        name = f"m_{s.args[0]}"
        keys = (*[k for k in f.keys if k != name], name)
        return replace(f, df=f.df.withColumn(name, F.col(f.position)), keys=keys)

    def _marked(self, f: Frontier, s: Step) -> Frontier:
        keep, name = s.args
        column = "origin" if name == "origin" else f"m_{name}"
        if column not in f.keys:
            raise BindError(f"{s}: this run keeps no {name}")
        same = F.col(f.position) == F.col(column)
        return replace(f, df=f.df.where(same if keep else ~same))

    def _unit(self, f: Frontier, s: Step) -> Frontier:
        return replace(f, df=f.df.withColumn("weight", F.lit(1).cast("long")))

    def _dedup(self, f: Frontier, s: Step) -> Frontier:
        by = [*f.keys, f.position] + (["label", "src", "dst", "far"] if f.kind == "E" else [])
        return replace(f, df=f.df.select(*by).distinct().withColumn("weight", F.lit(1).cast("long")), mode="bulk" if f.mode == "paths" else f.mode, fresh=True)

    def _rank(self, f: Frontier, s: Step) -> Frontier:
        (k,) = s.args
        f = self.bulk(f)
        order = [F.desc("weight"), F.asc(f.position)]
        if "origin" in f.keys:
            df = f.df.withColumn("rank", F.row_number().over(W.partitionBy("origin").orderBy(*order)))
            return replace(f, df=df.where(F.col("rank") <= k) if k else df)
        return replace(f, df=f.df.orderBy(*order).limit(k) if k else f.df.orderBy(*order))

    def _sample(self, f: Frontier, s: Step) -> Frontier:
        fraction, seed = s.args
        lot = F.conv(F.md5(F.concat_ws(":", f.position, F.lit(seed)).cast("binary")).substr(1, 12), 16, 10).cast("long")
        return replace(f, df=f.df.where(lot % 1_000_000 < int(fraction * 1_000_000)))

    def _simple_path(self, f: Frontier, s: Step) -> Frontier:
        if f.mode != "paths":
            raise BindError("simple_path needs a run in paths mode")
        return replace(f, df=f.df.where(F.size(F.array_distinct("path")) == F.size("path")))

    def _overlay(self, f: Frontier, s: Step) -> Frontier:
        after = self.after
        ends = [self._run_arm(f, a, after) for a in s.args[0]]
        return self._summed(ends)

    def _summed(self, ends: list[Frontier]) -> Frontier:
        out = ends[0].df
        for e in ends[1:]:
            out = out.unionByName(e.df, allowMissingColumns=ends[0].kind == "E")
        return self.bulk(replace(ends[0], df=out, fresh=False, literal=None))

    def _against(self, f: Frontier, s: Step) -> tuple[Frontier, DataFrame]:
        """f without marks that nothing needs any more, and how often (_w) the arm ends at each place."""
        arm, distinct = s.args
        if f.mode == "paths" and not distinct:
            raise BindError(f"{s}: paths are compared by their ends; give distinct=True")
        after = self.after
        end = self._run_arm(f, arm, after)
        f = self._forget(f, {k for k in f.keys if k not in end.keys})
        count = F.sum("weight") if end.kind != "E" else F.count("*")
        return f, end.df.groupBy(*end.keys, end.position).agg(count.alias("_w"))

    def _numbered(self, f: Frontier) -> DataFrame:
        """Rows mode: the rows of one place, numbered."""
        by = [*f.keys, f.position]
        return f.df.withColumn("_n", F.row_number().over(W.partitionBy(*by).orderBy("weight")))

    def _meet(self, f: Frontier, s: Step) -> Frontier:
        """Multiset intersection: the lesser multiplicity of each place; distinct: each common place once (in paths mode every path to one)."""
        f, other = self._against(f, s)
        by = [*f.keys, f.position]
        if f.mode == "paths":
            return replace(f, df=f.df.join(other, by, "left_semi"))
        if s.args[1]:
            return self._dedup(replace(f, df=f.df.join(other, by, "left_semi")), s)
        if f.mode == "rows" or f.kind == "E":
            return replace(f, df=self._numbered(f).join(other, by).where("_n <= _w").drop("_n", "_w"))
        return replace(f, df=f.df.join(other, by).withColumn("weight", F.least("weight", "_w")).drop("_w"))

    def _minus(self, f: Frontier, s: Step) -> Frontier:
        """Multiset difference; distinct: places that the arm does not reach keep what they have."""
        f, other = self._against(f, s)
        by = [*f.keys, f.position]
        if s.args[1]:
            return replace(f, df=f.df.join(other, by, "left_anti"))
        gone = F.coalesce("_w", F.lit(0))
        if f.mode == "rows" or f.kind == "E":
            return replace(f, df=self._numbered(f).join(other, by, "left").where(F.col("_n") > gone).drop("_n", "_w"))
        return replace(f, df=f.df.join(other, by, "left").withColumn("weight", F.col("weight") - gone).where("weight > 0").drop("_w"))

    def _branch(self, f: Frontier, s: Step) -> Frontier:
        key, op, value, then, otherwise = s.args
        after = self.after
        yes = self._run_arm(self._property(f, Step("property", (True, key, op, value))), then, after)
        no = self._run_arm(self._property(f, Step("property", (False, key, op, value))), otherwise, after)
        return self._summed([yes, no])

    def _repeat(self, f: Frontier, s: Step) -> Frontier:
        body, emit, max_depth = s.args
        tree = all(t.op != "edges" or (t.args[1] and all(self.graph.labels[x].tree for x in t.args[1] if x)) for t in body.steps)
        if max_depth is None and not tree:
            raise BindError(f"{s}: not known to end; give max_depth")
        after_loop = self.after | marks_used(body.steps)
        f = self._forget(f, {k for k in f.keys if k.startswith("m_") and k[2:] not in after_loop})
        found, here, depth = [], f, 0
        while max_depth is None or depth < max_depth:
            after = self._run_arm(here, body, after_loop)
            after = replace(after, df=stored(after.df, "round"), literal=None)
            depth += 1
            if after.df.isEmpty():
                break
            if emit == "last":  # who cannot go on stays
                stuck = here.df.join(self.run(Walk((body.steps[0],)), here, after_loop).df.select(F.col("src").alias("_s")).distinct(), F.col("pos") == F.col("_s"), "left_anti")
                found.append(stuck)
            else:
                found.append(after.df)
            here = after
        if emit == "last":
            found.append(here.df)
        out = found[0] if found else f.df.limit(0)
        for x in found[1:]:
            out = out.unionByName(x)
        return self.bulk(replace(f, df=out, fresh=False, literal=None))


def run(graph: PropertyGraph, spark: SparkSession, walk: Walk, ids=None, frame: DataFrame | None = None, per_origin: bool = False, mode: str = "bulk", rewrite: bool = True) -> DataFrame:
    """Apply a walk. Columns: origin (if kept), pos / eid, label, src, dst / value, weight, path (paths mode).

    ids or frame may be empty: the result then is, too. Unknown labels and keys raise.
    """
    kind_after(walk)
    walk = optimize(walk, graph)[0] if rewrite else walk
    low = Lowering(graph, spark)
    end = low.run(walk, low.start(ids, frame, per_origin, mode))
    marks = [k for k in end.keys if k.startswith("m_")]
    if marks:
        end = low.bulk(replace(end, df=end.df.drop(*marks), keys=tuple(k for k in end.keys if k not in marks), fresh=False))
    return end.df.drop("far")


def run_in_batches(graph: PropertyGraph, spark: SparkSession, walk: Walk, frame: DataFrame, paths: int) -> DataFrame:
    """The walk from every position of the frame, with origins: in as many batches of origins, by hash, as keep to about `paths` paths each.

    All origins belong to one batch. The paths are counted first, by the walk without origins and ranks; each batch's result is stored before the next begins.
    """
    counted = run(graph, spark, Walk(tuple(s for s in walk.steps if s.op in ("edges", "end"))), frame=frame).agg(F.sum("weight")).first()[0] or 0
    n = -(-counted // paths) or 1
    out = None
    for i in range(n):
        some = frame.where(F.pmod(F.xxhash64("pos"), F.lit(n)) == i)
        one = stored(run(graph, spark, walk, frame=some, per_origin=True), "batch")
        out = one if out is None else out.unionByName(one)
    return out


def touched(graph: PropertyGraph, spark: SparkSession, walk: Walk, ids) -> DataFrame:
    """Counters of one run: step, op, positions, weight after it; edges that it scanned; property cells that it read.

    The positions after each hop are stored, so that the plan grows with the steps, not with their square; one small aggregate per step follows, in one lazy union. An edge step scans the edges of its labels at the positions it starts from; a property step reads
    one cell of each position for every key it names.
    """
    kind_after(walk)
    low = Lowering(graph, spark, tracing=True)
    low.run(walk, low.start(ids))
    out = None
    for n, s, before, after in low.trace:
        one = after.df.agg(F.count("*").alias("positions"), F.coalesce(F.sum("weight"), F.lit(0)).cast("long").alias("weight"))
        edges = F.col("positions") if s.op in ("edges", "sample_out", "sample_in") else F.lit(0).cast("long")
        cells = F.lit(0).cast("long")
        if s.op in ("property", "properties", "values", "branch"):
            keys = len(s.args) if s.op == "properties" else 1
            one = one.crossJoin(F.broadcast(before.df.agg((F.count("*") * keys).alias("cells"))))  # one row each
            cells = F.col("cells")
        one = one.select(F.lit(n).alias("step"), F.lit(str(s)).alias("op"), "positions", "weight", edges.alias("edges"), cells.alias("cells"))
        out = one if out is None else out.unionByName(one)
    return out


def materialize_edge(graph: PropertyGraph, spark: SparkSession, walk: Walk, label: str, start: DataFrame, key: Column | None = None) -> PropertyGraph:
    """The walk from every start position becomes a stored edge with a weight; later walks that contain these steps use it."""
    from ..sources.graph import EdgeLabel

    ends = run(graph, spark, walk, frame=start, per_origin=True).select(F.col("origin").alias("src"), F.col("pos").alias("dst"), "weight")
    rows = stored(global_rank(ends, [F.asc("src"), F.asc("dst")], "eid"), label)
    edge = EdgeLabel(label, lambda: rows, ("weight",), weight="weight")
    return PropertyGraph(dict(graph.classes), graph.labels | {label: edge}, graph.virtual | {walk.steps: label})
