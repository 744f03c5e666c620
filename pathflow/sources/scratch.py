"""Lineage cuts: Parquet tables in the folder that driver and executors share."""

from __future__ import annotations

import hashlib
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """`spark.checkpoint.dir` of the session. Where it is unset, a run on one machine gets an own folder; a cluster raises, as its executors share none."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = "file://" + tempfile.mkdtemp(prefix="pathflow-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def _path(spark: SparkSession, name: str):
    path = spark._jvm.org.apache.hadoop.fs.Path(name)
    return path, path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())


def folder_state(spark: SparkSession, folder: str) -> str:
    """A digest of names, lengths and times of a folder's entries: it changes when a table is replaced or gets a file."""
    path, files = _path(spark, folder)
    seen = sorted((f.getPath().getName(), f.getLen(), f.getModificationTime()) for f in files.listStatus(path))
    return hashlib.md5(repr(seen).encode()).hexdigest()[:12]


def stored_bytes(df: DataFrame) -> int:
    """Bytes of the files that a table is read from."""
    total = 0
    for name in df.inputFiles():
        path, files = _path(df.sparkSession, name)
        total += files.getFileStatus(path).getLen()
    return total


@contextmanager
def shuffles_freed(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of what runs inside go as it ends, not when the driver happens to collect its garbage; a plan that runs again makes them again."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def stored(df: DataFrame, tag: str) -> DataFrame:
    """Compute once, write, read again: survives lost executors and keeps plans short."""
    path = f"{shared_dir(df.sparkSession)}/pathflow-graph/{tag}-{uuid.uuid4().hex}"
    with shuffles_freed(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


_KEPT: dict[tuple, DataFrame] = {}


def stored_once(spark: SparkSession, key: tuple, build) -> DataFrame:
    """A layout table of this application: built on first use, then read. The key names input folder and layout."""
    full = (spark.sparkContext.applicationId, *key)
    if full not in _KEPT:
        _KEPT[full] = stored(build(), "-".join(str(k).strip("/").split("/")[-1] for k in key))
    kept = _KEPT[full]
    return kept if kept.sparkSession is spark else spark.read.schema(kept.schema).parquet(*kept.inputFiles())
