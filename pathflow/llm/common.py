"""Shared helpers of the training-data operators: tables, shared scratch, words and their hashes."""

from __future__ import annotations

import ctypes
import gc
import sys
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: `spark.checkpoint.dir`. Where it is unset, a run on one machine gets an own folder; a
    cluster raises, as a folder of one machine would lose rows there."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = "file://" + tempfile.mkdtemp(prefix="pathflow-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def scratch_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/pathflow-scratch/{tag}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Cut lineage with one computation: a Parquet table in the shared folder, read again.

    Unlike an eager checkpoint it computes the plan once, is columnar and compressed, and keeps
    statistics for later joins. It survives lost executors.
    """
    spark = df.sparkSession
    path = scratch_path(spark, tag)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def discard(*frames: DataFrame | None) -> None:
    """Delete tables of `materialize` that nothing reads any more."""
    for df in frames:
        if df is not None and (path := getattr(df, "_scratch_path", None)):
            jvm = df.sparkSession._jvm
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(p, True)


def fresh(taken: list[str], *names: str) -> list[str]:
    """Names like `names` that are not in `taken`, whatever its case."""
    have, out = {c.lower() for c in taken}, []
    for name in names:
        while name.lower() in have:
            name += "_"
        out.append(name)
    return out


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z and nothing else."""
    return F.translate(text, UPPER, LOWER)


def id_crc(doc_id: Column) -> Column:
    """crc32 of the id as text; a null id counts as the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary"))


def text_words(text: str | None) -> list[bytes]:
    """Words of the text, A-Z lower-cased. `bytes.split` and `bytes.lower` know ASCII only, as the word rule does."""
    return [] if text is None else text.encode("utf-8", "surrogatepass").lower().split()


#: Bytes of text that a worker turns into Python values at once.
SLICE = 2 << 20


def slices(batch: pa.RecordBatch, limit: int = SLICE) -> Iterator[pa.RecordBatch]:
    """Slices of an Arrow batch with a bounded number of UTF-8 bytes in its column `text` (one row at least); nothing is copied."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column("text")), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at = 0
    while at < batch.num_rows:
        stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + limit, "right")))
        yield batch.slice(at, stop - at)
        at = stop


def give_back() -> None:
    """Return freed memory to the system at the end of a task: workers live on idle beside the next stage's JVM tasks, and allocators keep what was freed."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux" and (trim := getattr(ctypes.CDLL(None), "malloc_trim", None)):
        trim(0)


def over_slices(work: Callable[[pa.RecordBatch], pa.RecordBatch], limit: int = SLICE):
    """A function for `mapInArrow` that applies `work` slice by slice, so that a worker's memory follows the longest text, not the batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield from map(work, slices(batch, limit))
            del batch
        give_back()

    return run


def list_array(values: list[np.ndarray], kind: pa.DataType) -> pa.ListArray:
    """Arrays of numbers as one Arrow list column."""
    offsets = np.concatenate(([0], np.cumsum([len(v) for v in values], dtype=np.int64))).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(values) if values else [], kind))


class WordHashes(dict):
    """word -> signed 64-bit hash, kept for words seen lately: `limit` words of up to `longest` bytes each, about 25 MB in all."""

    limit, longest = 150_000, 64

    def __missing__(self, word: bytes) -> int:
        value = self.hashed(word)
        if len(word) <= self.longest:
            if len(self) >= self.limit:
                self.clear()
            self[word] = value
        return value

    @staticmethod
    def hashed(word: bytes) -> int:
        x = xxhash.xxh3_64_intdigest(word)
        return x - (1 << 64) if x >> 63 else x


def cutoff(counts: DataFrame, most: int) -> int:
    """The least value of `c` that at most `most` rows reach. Counts are binned (exact below 4096, 64 bins an octave above), so the driver gets
    a few thousand rows whatever the corpus."""
    c = F.col("c")
    bins = counts.groupBy(F.when(c < 4096, c).otherwise(4096 + F.floor((F.log2(c.cast("double")) - 12) * 64)).alias("bin")).agg(F.min("c").alias("least"), F.count("*").alias("n"))
    cut, taken = 1 << 62, 0
    for r in sorted(bins.collect(), key=lambda r: -r["bin"]):
        taken += r["n"]
        if taken > most:
            break
        cut = r["least"]
    return cut
