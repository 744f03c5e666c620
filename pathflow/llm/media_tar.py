"""Media columns: content-addressed payloads in tar shards; rows carry digest, offset and length.

A payload is stored as a lossless 8-bit greyscale PNG of width 64, named by the SHA-256 of its bytes, in tar shards in a
shared folder (any file system that pyarrow opens by URI). Writers store a payload once per shard and
emit a row only after its shard is closed, so rows never point at missing bytes; a lost executor's task writes new shards under new names. The index then keeps
one location for each digest. Range reads of 33 bytes fill its width and height without reading an image.

Null texts are empty ones: 64 zero bytes are stored. Rows that repeat get a row each and share one payload. An empty table gives no rows and no shard.
A long text is one payload, held whole by one worker (some six times its size). Extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
import struct
import tarfile
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, scratch_path, slices

WIDTH, HEADER = 64, 33
#: Fixed value: the PNG signature.
SIGNATURE = b"\x89PNG\r\n\x1a\n"


def payload_of(text: str | None) -> tuple[bytes, int]:
    """UTF-8 bytes, zero bytes up to a positive multiple of 64; and the length before that. Null: empty."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw + bytes(-len(raw) % WIDTH or (0 if raw else WIDTH)), len(raw)


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def encode_png(payload: bytes, level: int = 6) -> bytes:
    rows = len(payload) // WIDTH
    lines = np.zeros((rows, WIDTH + 1), np.uint8)  # the first byte of a line: no filter
    lines[:, 1:] = np.frombuffer(payload, np.uint8).reshape(rows, WIDTH)
    head = struct.pack(">IIBBBBB", WIDTH, rows, 8, 0, 0, 0, 0)
    return SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(lines.tobytes(), level)) + _chunk(b"IEND", b"")


def parse_header(head: bytes) -> tuple[int, int]:
    if head[:8] != SIGNATURE or head[12:16] != b"IHDR":
        raise ValueError("not a PNG header")
    return struct.unpack(">II", head[16:24])


def decode_png(media: bytes) -> bytes:
    width, height = parse_header(media[:HEADER])
    at, data = len(SIGNATURE), []
    while at < len(media):
        (n,), kind = struct.unpack(">I", media[at : at + 4]), media[at + 4 : at + 8]
        if kind == b"IDAT":
            data.append(media[at + 8 : at + 8 + n])
        at += 12 + n
    lines = np.frombuffer(zlib.decompress(b"".join(data)), np.uint8).reshape(height, width + 1)
    if lines[:, 0].any():
        raise ValueError("a filtered line")
    return lines[:, 1:].tobytes()


def _open(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


class ShardWriter:
    """One open tar shard; `add` returns the offset of the stored bytes."""

    def __init__(self, folder: str):
        files, path = _open(folder)
        files.create_dir(path, recursive=True)
        self.name = f"{uuid.uuid4().hex}.tar"
        self.out, self.at, self.have = files.open_output_stream(f"{path}/{self.name}"), 0, {}

    def add(self, digest: bytes, media: bytes) -> tuple[int, int]:
        info = tarfile.TarInfo(f"{digest.hex()}.png")
        info.size = len(media)
        self.out.write(info.tobuf(tarfile.USTAR_FORMAT))
        offset = self.at + tarfile.BLOCKSIZE
        self.out.write(media)
        self.out.write(bytes(-len(media) % tarfile.BLOCKSIZE))
        self.at = offset + len(media) + -len(media) % tarfile.BLOCKSIZE
        self.have[digest] = offset, len(media)
        return self.have[digest]

    def close(self) -> None:
        self.out.write(bytes(2 * tarfile.BLOCKSIZE))
        self.out.close()


def store_media(docs: DataFrame, folder: str, id_col: str = "doc_id", text_col: str = "text", shard_bytes: int = 64 << 20) -> DataFrame:
    """Writes the shards; doc rows: id, n_bytes, digest, shard, offset, length."""

    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        writer, ids, rows = None, [], []

        def flush() -> pa.RecordBatch:
            writer.close()
            columns = zip(*rows, strict=True)
            made = [pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.binary(), pa.string(), pa.int64(), pa.int64()), strict=True)]
            return pa.RecordBatch.from_arrays([pa.concat_arrays(ids), *made], ["id", "n_bytes", "digest", "shard", "offset", "length"])

        for batch in batches:
            for part in slices(batch):
                for i, text in enumerate(part.column("text").to_pylist()):
                    writer = writer or ShardWriter(folder)
                    payload, n = payload_of(text)
                    digest = hashlib.sha256(payload).digest()
                    at = writer.have.get(digest) or writer.add(digest, encode_png(payload))
                    ids.append(part.column("id").slice(i, 1))
                    rows.append((n, digest, writer.name, *at))
                    if writer.at >= shard_bytes:
                        yield flush()
                        writer, ids, rows = None, [], []
        if writer:
            yield flush()

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, f"id {kind}, n_bytes long, digest binary, shard string, offset long, length long").withColumnRenamed("id", id_col)


def media_index(rows: DataFrame) -> DataFrame:
    """One location for each digest: the content address decides, not the row."""
    at = rows.groupBy("digest").agg(F.min(F.struct("shard", "offset", "length")).alias("at"))
    return at.select("digest", "at.*")


_HEAD = {"digest": pa.binary(), "shard": pa.string(), "offset": pa.int64(), "length": pa.int64(), "width": pa.int32(), "height": pa.int32()}
_HEAD_TYPE = "digest binary, shard string, offset long, length long, width int, height int"
_BODY = {"digest": pa.binary(), "width": pa.int32(), "height": pa.int32(), "payload_bytes": pa.int64(), "payload_sha256": pa.string(), "tail_crc32": pa.int64(), "media_bytes": pa.int64(), "media_sha256": pa.string(), "feature": pa.string()}
_BODY_TYPE = "digest binary, width int, height int, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _header(source, digest: bytes, shard: str, offset: int, length: int) -> tuple:
    return (digest, shard, offset, length, *parse_header(source.read_at(HEADER, offset)))


def _body(source, digest: bytes, shard: str, offset: int, length: int) -> tuple:
    media = source.read_at(length, offset)
    width, height = parse_header(media[:HEADER])
    payload = decode_png(media)
    a = np.frombuffer(payload, np.uint8)
    feature = f"grey8 {width}x{height} mean={a.mean():.4f} sd={a.std():.4f} kinds={np.count_nonzero(np.bincount(a, minlength=256))}"
    return (digest, width, height, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-WIDTH:]), len(media), hashlib.sha256(media).hexdigest(), feature)


def _read(folder: str, take, columns: dict[str, pa.DataType]):
    """Rows made by `take` at each location; one shard is open at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, path = _open(folder)
        name, source = None, None
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                out = []
                for place in zip(*[batch.column(c).slice(at, 1024).to_pylist() for c in ("digest", "shard", "offset", "length")], strict=True):
                    if place[1] != name:
                        if source:
                            source.close()
                        name, source = place[1], files.open_input_file(f"{path}/{place[1]}")
                    out.append(take(source, *place))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), columns.values(), strict=True)], list(columns))
        if source:
            source.close()

    return run


def read_headers(index: DataFrame, folder: str) -> DataFrame:
    """The index (digest, shard, offset, length) with width and height of every stored payload, by range reads of the header alone."""
    return _dealt(index, HEADER).mapInArrow(_read(folder, _header, _HEAD), _HEAD_TYPE)


def read_media(index: DataFrame, folder: str) -> DataFrame:
    """Reads the stored bytes back: width, height, digests of payload and stored form, features."""
    return _dealt(index, None).mapInArrow(_read(folder, _body, _BODY), _BODY_TYPE)


def _dealt(index: DataFrame, read: int | None, task_bytes: int = 32 << 20, run_bytes: int = 4 << 20) -> DataFrame:
    """Runs of about `run_bytes` of a shard, dealt to tasks by the bytes that will be read (`read` a payload, else its length), in file order."""
    total = index.agg(F.sum(F.lit(read + 512) if read else F.col("length"))).first()[0] or 0
    run = F.floor(F.col("offset") / run_bytes)
    return index.withColumn("_run", run).repartition(max(1, -(-total // task_bytes)), "shard", "_run").sortWithinPartitions("shard", "offset").drop("_run")


def media_columns(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", folder: str | None = None) -> DataFrame:
    """One row per document (repeats included): id, n_bytes, width and height from the headers, and what reading the stored bytes back gives. Equal
    texts, equal values."""
    folder = folder or scratch_path(docs.sparkSession, "media")
    rows = materialize(store_media(docs, folder, id_col, text_col), "media-rows")
    index = materialize(media_index(rows), "media-index")
    heads = read_headers(index, folder).select("digest", "width", "height")
    back = read_media(index, folder).drop("width", "height")
    return rows.select(id_col, "n_bytes", "digest").join(heads.join(back, "digest"), "digest").drop("digest")
