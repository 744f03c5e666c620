"""Byte-level BPE by corpus-level merge replay.

Texts are cut into pieces by the tokenizer's pattern. Pieces never span from a non-blank to a blank, so texts are first cut at blanks (cheap)
and the pattern is applied to distinct segments only; texts in which white space precedes a blank go through the pattern whole.

Segments are counted over the whole corpus. The most frequent ones (`most`, a bound on what is broadcast) are replayed once for the corpus, in
parallel, and serve every document. What is rarer is replayed once a slice of text, together with the other rare pieces there. The choice moves work
only: ids do not depend on it.

Replay: a block of distinct pieces lies in one row; an inverted index maps every adjacent pair that has a rank to its places there (the pairs of bytes are
found by one table lookup over the row); a heap yields ranks in order; a merge touches only its two neighbours and files the new pairs in the index. Should a merge create a pair that ranks *below* the current
one (possible, as a token may have several splits), that piece alone is finished at once by least rank first, as the order inside a piece demands.

Memory of a worker: the ranks, the frequent segments, one slice and a cache of rare segments that is bounded by bytes; all go with the task.
Null texts are empty: no tokens. An empty table gives no rows. Rows that repeat are encoded each. A long text is one slice of its own: about
40 bytes a byte of it. Extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cutoff, discard, give_back, list_array, materialize, slices

#: Broadcast bound: a rank file has this many entries at most.
MAX_RANKS = 1_000_000
#: Bytes of text that are cut into segments at once: their strings take ten times as much, beside the ranks and the frequent segments.
SLICE = 512 << 10


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
    if len(ranks) > MAX_RANKS:
        raise ValueError(f"{path} has {len(ranks)} ranks; at most {MAX_RANKS} are broadcast")
    return ranks


class MergeReplay:
    """Encodes and decodes with one tokenizer. `frequent`: packed ids of known segments (after a blank)."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, frequent: dict[str, bytes] | None = None, cache_bytes: int = 4 << 20):
        self.ranks, self.pattern, self.frequent, self.cache_bytes = ranks, regex.compile(pattern), frequent or {}, cache_bytes
        self.vocabulary = {i: t for t, i in ranks.items()}
        self.packed = {t: i.to_bytes(4, "little") for t, i in ranks.items()}
        self.rare: dict[str, bytes] = {}  # segments after a blank, without it
        self.held = 0  # bytes of their texts and ids
        self.odd = re.compile(r"\s ")
        # ranks of pairs of bytes. 255 is in no UTF-8: it stands for an edge, a run of it that is in no token, so nothing merges with an edge
        self.pairs = np.full((256, 256), -1, np.int64)
        for t, i in ranks.items():
            if len(t) == 2:
                self.pairs[t[0], t[1]] = i
        self.pairs[255, :] = self.pairs[:, 255] = -1
        run = b"\xff"
        while any(run in t for t in ranks):
            run += b"\xff"
        self.single = [*(bytes([x]) for x in range(255)), run]

    def _finish(self, parts: list[bytes]) -> list[bytes]:
        """Least rank first, leftmost first, in one piece."""
        while True:
            best = min(((r, i) for i in range(len(parts) - 1) if (r := self.ranks.get(parts[i] + parts[i + 1])) is not None), default=None)
            if best is None:
                return parts
            i = best[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]

    def encode_pieces(self, pieces: list[str], block: int = 8192) -> dict[str, bytes]:
        """Packed little-endian 32-bit ids of distinct pieces. Each block has an index of its own, so memory follows the block."""
        out: dict[str, bytes] = {}
        for at in range(0, len(pieces), block):
            self._replay(pieces[at : at + block], out)
        return out

    def _replay(self, pieces: list[str], out: dict[str, bytes]) -> None:
        get, packed, vocabulary, edge = self.ranks.get, self.packed, self.vocabulary, self.single[255]
        names: list[str] = []
        raws: list[bytes] = []
        for piece in pieces:
            raw = piece.encode("utf-8", "surrogatepass")
            if raw in packed:
                out[piece] = packed[raw]
            else:
                names.append(piece)
                raws.append(raw)
        # all pieces in one row of bytes, an edge before and after each; a merged token's other bytes become None
        row = b"\xff" + b"\xff".join(raws) + b"\xff"
        tokens: list = list(map(self.single.__getitem__, row))
        codes = np.frombuffer(row, np.uint8)
        first = self.pairs[codes[:-1], codes[1:]]
        order = np.argsort(first, kind="stable")
        order = order[np.searchsorted(first[order], 0) :]
        heap, starts = (x.tolist() for x in np.unique(first[order], return_index=True))
        order = order.tolist()
        index = {r: order[b:e] for r, b, e in zip(heap, starts, [*starts, len(order)][1:], strict=True)}
        known, pop, push = index.get, heapq.heappop, heapq.heappush
        while heap:
            rank = pop(heap)
            token = vocabulary[rank]
            size = len(token)
            for i in sorted(index.pop(rank)):
                left = tokens[i]
                # the place is stale unless its two tokens still make this one
                if left is None or left + tokens[j := i + len(left)] != token:
                    continue
                tokens[i], tokens[j] = token, None
                lower = False
                if (r := get(token + tokens[i + size])) is not None:
                    lower = r <= rank
                    if (places := known(r)) is None:
                        index[r] = [i]
                        push(heap, r)
                    else:
                        places.append(i)
                p = i - 1
                while (before := tokens[p]) is None:
                    p -= 1
                if (r := get(before + token)) is not None:
                    lower = lower or r <= rank
                    if (places := known(r)) is None:
                        index[r] = [p]
                        push(heap, r)
                    else:
                        places.append(p)
                if lower:
                    b, e = i, i
                    while tokens[b - 1] is not edge:
                        b -= 1
                    while tokens[e] is not edge:
                        e += 1
                    done = self._finish([t for t in tokens[b:e] if t is not None])
                    tokens[b:e] = [x for t in done for x in (t, *[None] * (len(t) - 1))]
        at = 1
        for name, raw in zip(names, raws, strict=True):
            out[name] = b"".join(map(packed.__getitem__, filter(None, tokens[at : at + len(raw)])))
            at += len(raw) + 1

    def encode_segments(self, segments: list[str], blank: str) -> list[bytes]:
        """Packed ids of distinct segments, each behind `blank`; their distinct pieces are replayed together."""
        cut = [self.pattern.findall(blank + s) for s in segments]
        get = self.encode_pieces(sorted({p for c in cut for p in c})).__getitem__
        return [b"".join(map(get, c)) for c in cut]

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """Packed ids of every text."""
        split = [None if self.odd.search(t) else t.split(" ") for t in texts]
        # a leading blank makes an empty first segment, which has no pieces
        heads = sorted({s[0] for s in split if s})
        first = dict(zip(heads, self.encode_segments(heads, ""), strict=True))
        whole = [self.pattern.findall(t) if s is None else None for t, s in zip(texts, split, strict=True)]
        pieces = self.encode_pieces(sorted({p for w in whole if w for p in w}))
        if self.held > self.cache_bytes:
            self.rare, self.held = {}, 0
        new = sorted(set().union(*(s[1:] for s in split if s)) - self.frequent.keys() - self.rare.keys()) if split else []
        for s, ids in zip(new, self.encode_segments(new, " "), strict=True):
            self.rare[s] = ids
            self.held += len(s) + len(ids)
        known, rare = self.frequent.get, self.rare.__getitem__
        return [b"".join(map(pieces.__getitem__, w)) if s is None else first[s[0]] + b"".join([known(x) or rare(x) for x in s[1:]]) for s, w in zip(split, whole, strict=True)]

    def decode(self, packed: bytes) -> bytes:
        return b"".join(map(self.vocabulary.__getitem__, np.frombuffer(packed, "<u4").tolist()))


def _segment_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Segments that a slice holds twice or more, with their counts; those met once cannot be worth a place."""
    odd = re.compile(r"\s ")
    for batch in batches:
        for part in slices(batch, 8 << 20):
            counts = Counter()
            for t in part.column("text").to_pylist():
                if t and not odd.search(t):
                    counts.update(t.split(" ")[1:])
            often = [(s, n) for s, n in counts.items() if n > 1 and len(s) <= 64]
            yield pa.RecordBatch.from_arrays([pa.array([s for s, _ in often], pa.string()), pa.array([n for _, n in often], pa.int64())], ["segment", "n"])
            del counts, often
    give_back()


def frequent_segments(docs: DataFrame, ranks: dict[bytes, int], pattern: str, text_col: str = "text", most: int = 131_072) -> dict[str, bytes]:
    """The corpus's most frequent segments and their packed ids, replayed in parallel: `most` entries of 64 characters at most reach the driver."""
    texts = docs.select(F.col(text_col).alias("text")).where("text IS NOT NULL")
    counts = materialize(texts.mapInArrow(_segment_counts, "segment string, n long").groupBy("segment").agg(F.sum("n").alias("c")), "segments")
    shared = docs.sparkSession.sparkContext.broadcast(ranks)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        replay = MergeReplay(shared.value, pattern)
        for batch in batches:
            segments = batch.column("segment").to_pylist()
            yield pa.RecordBatch.from_arrays([batch.column("segment"), pa.array(replay.encode_segments(segments, " "), pa.binary())], ["segment", "ids"])
            del batch, segments
        del replay
        give_back()

    top = counts.where(F.col("c") >= cutoff(counts, most)).select("segment")
    found = {r["segment"]: bytes(r["ids"]) for r in top.repartition(8).mapInArrow(run, "segment string, ids binary").toLocalIterator()}
    discard(counts)
    shared.destroy()
    return found


def _encoded(docs: DataFrame, ranks_path: str, pattern: str, id_col: str, text_col: str, make, schema: str) -> DataFrame:
    """id and what `make` gives for the packed ids of each row."""
    ranks = load_ranks(ranks_path)
    shared = docs.sparkSession.sparkContext.broadcast((ranks, frequent_segments(docs, ranks, pattern, text_col)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        replay = MergeReplay(shared.value[0], pattern, shared.value[1])
        for batch in batches:
            for part in slices(batch, SLICE):
                packed = replay.encode_batch([t or "" for t in part.column("text").to_pylist()])
                columns = make(packed, replay)
                yield pa.RecordBatch.from_arrays([part.column("id"), *columns.values()], ["id", *columns])
                del part, packed, columns
            del batch
        # the worker lives on beside later stages: what the task made goes first, then it is given back
        del replay
        give_back()

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = docs.schema[id_col].dataType.simpleString()
    return rows.mapInArrow(run, f"id {kind}, {schema}").withColumnRenamed("id", id_col)


def encode_digests(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_tokens, ids_sha256, decoded_sha256 (of the bytes decoded from the ids); one row for each row of `docs`."""

    def make(packed: list[bytes], replay: MergeReplay) -> dict[str, pa.Array]:
        return {
            "n_tokens": pa.array([len(p) // 4 for p in packed], pa.int64()),
            "ids_sha256": pa.array([hashlib.sha256(p).hexdigest() for p in packed], pa.string()),
            "decoded_sha256": pa.array([hashlib.sha256(replay.decode(p)).hexdigest() for p in packed], pa.string()),
        }

    return _encoded(docs, ranks_path, pattern, id_col, text_col, make, "n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, token_ids array<int>; one row for each row of `docs`."""

    def make(packed: list[bytes], _) -> dict[str, pa.Array]:
        return {"token_ids": list_array([np.frombuffer(p, "<i4") for p in packed], pa.int32())}

    return _encoded(docs, ranks_path, pattern, id_col, text_col, make, "token_ids array<int>")


def decode(encoded: DataFrame, ranks_path: str, id_col: str = "doc_id", ids_col: str = "token_ids") -> DataFrame:
    """id, text: the decoded bytes as UTF-8 (bytes that are no UTF-8 become replacement marks); null ids give null."""
    vocabulary = encoded.sparkSession.sparkContext.broadcast({i: t for t, i in load_ranks(ranks_path).items()})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        get = vocabulary.value.__getitem__
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = [None if x is None else b"".join(map(get, x)).decode("utf-8", "replace") for x in part.column("ids").to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(texts, pa.string())], ["id", "text"])

    rows = encoded.select(F.col(id_col).alias("id"), F.col(ids_col).alias("ids"))
    kind = encoded.schema[id_col].dataType.simpleString()
    return rows.mapInArrow(run, f"id {kind}, text string").withColumnRenamed("id", id_col)
