"""The event stream as edges user -> event type: windows, sessions, dedup, joins, kept counts.

Every query runs with `availableNow` over a folder of files and writes to a Parquet or memory sink through `drain`; its batch twin
is the reference. Timestamps come without a zone, so they are cast before a watermark.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from itertools import groupby

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..sources.scratch import shared_dir

SCHEMA = "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING"


def read_stream(spark: SparkSession, folder: str, glob: str = "*.parquet", files_a_batch: int = 1000) -> DataFrame:
    raw = spark.readStream.schema(SCHEMA).option("pathGlobFilter", glob).option("maxFilesPerTrigger", files_a_batch).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream to the end of its input; the rows of its sink as a batch table.

    append goes to Parquet files in the shared folder; update and complete keep the last row set of foreachBatch.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/pathflow-stream/{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{base}/checkpoint").outputMode(mode).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", f"{base}/out").start()
    else:
        query = writer.foreachBatch(lambda df, epoch: df.withColumn("_epoch", F.lit(epoch)).write.mode("append").parquet(f"{base}/out")).start()
    query.awaitTermination()
    out = spark.read.schema(stream.schema if mode == "append" else stream.schema.add("_epoch", "long")).parquet(f"{base}/out")
    return out


def tumbling(stream: DataFrame, width: str = "1 hour", delay: str = "10 minutes") -> DataFrame:
    w = stream.withWatermark("ts", delay).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("edges"))
    return w.select(F.col("window.start").alias("start"), "event_type", "edges")


def sliding(stream: DataFrame, width: str = "2 hours", step: str = "1 hour", delay: str = "10 minutes") -> DataFrame:
    w = stream.withWatermark("ts", delay).groupBy(F.window("ts", width, step)).agg(F.count("*").alias("edges"))
    return w.select(F.col("window.start").alias("start"), "edges")


def sessions(stream: DataFrame, gap: str = "2 hours", delay: str = "10 minutes") -> DataFrame:
    w = stream.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("edges"))
    return w.select("user_id", F.col("session_window.start").alias("start"), "edges")


def deduplicated(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def static_hop(stream: DataFrame, edges: DataFrame) -> DataFrame:
    """One walk step from each event's user over stored edges (src, dst)."""
    return stream.join(edges, stream.user_id == edges.src).select("event_id", F.col("dst").alias("part"))


def interval_join(stream: DataFrame, first: str = "view", then: str = "purchase", within: str = "1 hour", delay: str = "10 minutes") -> DataFrame:
    a = stream.where(F.col("event_type") == first).select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", delay)
    b = stream.where(F.col("event_type") == then).select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", delay)
    return a.join(b, F.expr(f"ua = ub AND tb >= ta AND tb <= ta + INTERVAL {within}")).select("a", "b")


def kept_counts(stream: DataFrame) -> DataFrame:
    """Edges per (user, event type), kept up to date across batches by custom state."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = state.get[0] if state.exists else 0
        n += sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "event_type": [key[1]], "edges": [n]})

    return stream.groupBy("user_id", "event_type").applyInPandasWithState(step, "user_id long, event_type string, edges long", "n long", "update", GroupStateTimeout.NoTimeout)


def _counted(people: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    people, n = np.unique(people, return_counts=True)
    return people, n.astype("int64")


class _SharedPairs(StatefulProcessor):
    """Per block of a resource: its members and their counts in the state store, and what a batch adds as products of lists of people.

    A block sees every new edge of its resource but keeps those of its own people. New edges meet the kept edges of earlier batches in the one block
    that keeps them, and new edges of the same batch in the block of the lesser person, so a pair of edges counts once whatever the order of rows.
    """

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.members = handle.getValueState("members", "people binary, n binary")

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        seen = [(r["person"].to_numpy("int64"), r["own"].to_numpy("int64") > 0) for r in rows]
        people, own = (np.concatenate(c) for c in zip(*seen))
        (new, new_n), (mine, mine_n) = _counted(people), _counted(people[own])
        if self.members.exists():
            old, old_n = (np.frombuffer(c, "int64") for c in self.members.get())
            yield pd.DataFrame({"left": [old], "left_n": [old_n], "right": [new], "right_n": [new_n], "ordered": [False]})
        else:
            old = old_n = np.empty(0, "int64")
        if len(mine):
            yield pd.DataFrame({"left": [mine], "left_n": [mine_n], "right": [new], "right_n": [new_n], "ordered": [True]})
            kept, place = np.unique(np.concatenate([old, mine]), return_inverse=True)
            n = np.zeros(len(kept), "int64")
            np.add.at(n, place, np.concatenate([old_n, mine_n]))
            self.members.update((kept.tobytes(), n.tobytes()))

    def close(self) -> None:
        pass


def shared_products(stream: DataFrame, resource: list[str], blocks: int = 4) -> DataFrame:
    """What each batch of edges adds to the shared counts of pairs of people, as products: (left, left_n, right, right_n, ordered), sorted lists of people and
    their counts. Every person on the left shares left_n * right_n with every other on the right; where ordered, with the greater ones only.

    A resource's people are dealt to `blocks` keys, each edge is sent to all of them. Edges without a person are left out; a null resource is none. The members
    live in the state store, in RocksDB; a task holds those of one block, and no pair is made here.
    """
    edges = stream.where(" AND ".join(f"`{c}` IS NOT NULL" for c in ("user_id", *resource)))
    home = F.pmod(F.xxhash64("user_id"), F.lit(blocks)).cast("int")
    dealt = edges.select(*resource, F.col("user_id").alias("person"), home.alias("home"), F.explode(F.array(*map(F.lit, range(blocks)))).alias("block"))
    dealt = dealt.select(*resource, "block", "person", (F.col("home") == F.col("block")).cast("int").alias("own"))
    lists = "left array<long>, left_n array<long>, right array<long>, right_n array<long>, ordered boolean"
    return dealt.groupBy(*resource, "block").transformWithStateInPandas(_SharedPairs(), lists, "Append", "None")


def shared_changes(stream: DataFrame, resource: list[str], blocks: int = 4) -> DataFrame:
    """What each batch of edges adds to the shared counts of pairs a < b of people: their sum by pair is the number of pairs of edges that meet in a resource.
    The rows of `shared_products`, multiplied out; each block is a task of its own, so a hot resource is no single one."""
    p = shared_products(stream, resource, blocks)
    left = p.select(F.explode(F.arrays_zip("left", "left_n")).alias("l"), "right", "right_n", "ordered")
    both = left.select("l", "ordered", F.explode(F.arrays_zip("right", "right_n")).alias("r")).where("IF(ordered, l.left < r.right, l.left <> r.right)")
    return both.select(F.least("l.left", "r.right").alias("a"), F.greatest("l.left", "r.right").alias("b"), (F.col("l.left_n") * F.col("r.right_n")).alias("shared"))


def shared_totals(products: DataFrame, pairs: int = 50_000_000) -> DataFrame:
    """(a, b, shared): the sum of all changes of `shared_products` (a batch table) by pair a < b of people.

    People are cut into ranges, and every two ranges are a key of about `pairs` products. A task sums one person's products in an array, so neither products
    nor sums cross the network, only the lists, once per range that they meet.
    """
    size = products.agg(F.sum(F.size("left").cast("long") * F.size("right"))).first()[0] or 0
    keys = max(min(2 * products.sparkSession.sparkContext.defaultParallelism, size // 100_000), size // pairs, 1)
    n = int(np.ceil((np.sqrt(8 * keys + 1) - 1) / 2))
    new = products.where("ordered").select(F.explode("right").alias("person"))
    bounds = np.array(sorted({int(x) for x in new.approxQuantile("person", [i / n for i in range(1, n)], 0.1 / n)}) if n > 1 else [], "int64")
    n = len(bounds) + 1
    dealt = products.mapInArrow(lambda batches: _dealt(batches, bounds), "key int, left binary, left_n binary, right binary, right_n binary")
    return dealt.repartition(n * (n + 1) // 2, "key").sortWithinPartitions("key").mapInArrow(_summed, "a long, b long, shared long")


def _dealt(batches: Iterator[pa.RecordBatch], bounds: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Directed products of ranges i <= j of people, of which those from a lesser to a greater person count."""
    schema = pa.schema([("key", pa.int32()), *[(c, pa.binary()) for c in ("left", "left_n", "right", "right_n")]])
    n = len(bounds) + 1

    def pieces(people: np.ndarray, counts: np.ndarray) -> list[tuple[bytes, bytes]]:
        cuts = [0, *np.searchsorted(people, bounds, "right"), len(people)]
        return [(people[i:j].tobytes(), counts[i:j].tobytes()) for i, j in zip(cuts, cuts[1:])]

    for batch in batches:
        ordered, rows, held = batch.column("ordered").to_pylist(), [], 0
        lists = [batch.column(c) for c in ("left", "left_n", "right", "right_n")]
        for r, up in enumerate(ordered):
            left, left_n, right, right_n = (c[r].values.to_numpy() for c in lists)
            one, other = pieces(left, left_n), pieces(right, right_n)
            for x, y in [(one, other)] if up else [(one, other), (other, one)]:
                for i in range(n):
                    for j in range(i, n):
                        if x[i][0] and y[j][0]:
                            rows.append((i * n + j, *x[i], *y[j]))
                            held += len(x[i][0]) + len(y[j][0])
            if held > 1 << 22:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), schema.types)], schema=schema)
                rows, held = [], 0
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), schema.types)], schema=schema)


def _summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by key: each key's products are summed when all are there."""
    names = ("left", "left_n", "right", "right_n")

    def rows() -> Iterator[tuple]:
        for batch in batches:
            keys, columns = batch.column("key").to_pylist(), [batch.column(c) for c in names]
            for r, key in enumerate(keys):
                yield (key, *(np.frombuffer(c[r].as_py(), "int64") for c in columns))

    for _, group in groupby(rows(), lambda r: r[0]):
        yield from _sum_of_key([r[1:] for r in group])


def _sum_of_key(products: list[tuple], rows_a_batch: int = 200_000) -> Iterator[pa.RecordBatch]:
    sizes = np.array([len(p[2]) for p in products])
    ends = np.cumsum(sizes)
    people, code = np.unique(np.concatenate([p[2] for p in products]), return_inverse=True)
    times = np.concatenate([p[3] for p in products])
    left, left_n = np.concatenate([p[0] for p in products]), np.concatenate([p[1] for p in products])
    row = np.repeat(np.arange(len(products)), [len(p[0]) for p in products])
    order = np.argsort(left, kind="stable")
    left, left_n, row = left[order], left_n[order], row[order]
    single = left_n.max() == 1 and times.max() == 1
    # sums in doubles are exact below 2^53
    small = sum(int(p[1].sum()) * int(p[3].sum()) for p in products) < 1 << 53
    starts = np.flatnonzero(np.r_[True, left[1:] != left[:-1]])
    first = np.searchsorted(people, left[starts], "right")
    out, held = [], 0
    for s, e, low in zip(starts, np.r_[starts[1:], len(left)], first):
        met = [slice(ends[r] - sizes[r], ends[r]) for r in row[s:e]]
        codes = np.concatenate([code[m] for m in met])
        shares = None if single else np.concatenate([times[m] * k for m, k in zip(met, left_n[s:e])])
        if 8 * len(codes) < len(people):
            codes, place = np.unique(codes, return_inverse=True)
        else:
            place, codes = codes, np.arange(len(people))
        if shares is None or small:
            total = np.bincount(place, shares, len(codes)).astype("int64")
        else:
            total = np.zeros(len(codes), "int64")
            np.add.at(total, place, shares)
        kept = np.flatnonzero((total > 0) & (codes >= low))
        if len(kept):
            out.append((np.full(len(kept), left[s]), people[codes[kept]], total[kept]))
            held += len(kept)
        if held >= rows_a_batch:
            yield _pairs(out)
            out, held = [], 0
    if out:
        yield _pairs(out)


def _pairs(parts: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), pa.int64()) for c in zip(*parts)], ["a", "b", "shared"])


@contextmanager
def rocksdb(spark: SparkSession) -> Iterator[None]:
    """The state store that `shared_products` needs, for the queries started inside; the session's own setting comes back."""
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name)
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def latest(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Of an update stream's rows, the last of each key."""
    others = [c for c in rows.columns if c not in (*keys, "_epoch")]
    return rows.groupBy(*keys).agg(*[F.max_by(c, "_epoch").alias(c) for c in others])


def in_files(spark: SparkSession, events: DataFrame, cuts: list[Callable[[DataFrame], DataFrame]]) -> str:
    """A folder with one file per cut, written in order: a replayable stream."""
    folder = f"{shared_dir(spark)}/pathflow-stream/{uuid.uuid4().hex}-in"
    for cut in cuts:
        cut(events).coalesce(1).write.mode("append").parquet(folder)
    return folder
