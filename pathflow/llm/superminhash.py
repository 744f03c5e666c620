"""Near duplicates by SuperMinHash: signatures, banding, verification on full sets, components.

Signature (Ertl's SuperMinHash): every element draws, level by level, a fresh slot of one random
permutation and a value `level + uniform`; a slot keeps its least value. As soon as all slots hold a value
below the next level no further draw can win, so levels end early; sets of n >> m elements need one or two.

Banding: 32 bands of 4 rows; a pair at Jaccard 0.8 misses every band with probability (1 - 0.8^4)^32 < 1e-7.
Only one document of each distinct shingle set takes part, and of buckets with the same members only one.
Buckets are resolved without emitting all pairs: first every member is compared with its bucket's least one, and verified links merge
components. What is then left of a bucket (members in several components) goes through blocks: members are dealt to blocks of
about 512 members or half a million shingles, each pair of blocks is one small task that holds nothing else, compares members of different components by an inverted index
of their full sets, and gives back a spanning forest of the links. Every pair of a bucket is thus connected or compared; groups of
copies die after the first step with as many comparisons as members.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHashes, discard, give_back, list_array, materialize, over_slices, slices, text_words
from .components import connected_components, relabel

GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def mix64(x: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_set(words: list[bytes], k: int, hashes: WordHashes) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the k-word shingles; of the whole sequence if it is shorter."""
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(hashes.__getitem__, words), np.int64, n).view(np.uint64)
    k = min(k, n)
    x = np.full(n - k + 1, k, np.uint64)
    for i in range(k):
        x = mix64(x * GOLDEN + h[i : n - k + 1 + i])
    return np.unique(x)


def signature(elements: np.ndarray, m: int = 128, block: int = 16_384) -> np.ndarray:
    """SuperMinHash of a set of 64-bit elements: m values `level << 32 | uniform`.

    An element's draws depend on the element alone, so blocks of elements fold into the same slots one after another: memory is that of one
    block, and later blocks stop earlier.
    """
    best = np.full(m, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(elements), block):
        part = elements[at : at + block]
        rows = np.arange(len(part))
        perm = np.tile(np.arange(m, dtype=np.uint8 if m <= 256 else np.uint16), (len(part), 1))
        for level in range(m):
            if best.max() < np.uint64(level << 32):
                break
            x = mix64(part + np.uint64((level + 1) * int(GOLDEN) & (2**64 - 1)))
            k = level + ((x >> np.uint64(40)) % np.uint64(m - level)).astype(np.int64)
            slot = perm[rows, k]
            perm[rows, k] = perm[:, level]
            np.minimum.at(best, slot, (x & np.uint64(0xFFFFFFFF)) | np.uint64(level << 32))
    return best


def band_keys(sig: np.ndarray, bands: int) -> np.ndarray:
    x = np.arange(1, bands + 1, dtype=np.uint64) * GOLDEN
    for column in sig.reshape(bands, -1).T:
        x = mix64(x * GOLDEN + column)
    return x.view(np.int64)


def _sketches(shingle: int, m: int, bands: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()

        def work(part: pa.RecordBatch) -> pa.RecordBatch:
            n, prints, keys = [], [], []
            for text in part.column("text").to_pylist():
                s = shingle_set(text_words(text), shingle, hashes)
                n.append(len(s))
                prints.append(np.frombuffer(hashlib.blake2b(s.tobytes(), digest_size=16).digest(), np.int64))
                keys.append(band_keys(signature(s, m), bands) if len(s) else np.empty(0, np.int64))
            a, b = (pa.array([int(x[i]) if c else None for x, c in zip(prints, n, strict=True)], pa.int64()) for i in range(2))
            return pa.RecordBatch.from_arrays([part.column("id"), pa.array(n, pa.int64()), a, b, list_array(keys, pa.int64())], ["id", "n", "set_a", "set_b", "keys"])

        yield from over_slices(work)(batches)
        hashes.clear()
        give_back()

    return run


#: Bits of the broadcast id mask, at most (8 MB); and bits kept for each id.
MASK_BITS, BITS_AN_ID = 1 << 26, 16


def _id_mask(ids: DataFrame) -> tuple[int, bytes] | None:
    """(modulus, bits): set where `id % modulus` is a candidate's. None where the candidates would fill the bounded mask too densely.

    Texts of other documents then need not cross the network; what slips through costs a set that nothing asks for.
    """
    n = ids.count()
    if n * BITS_AN_ID // 2 > MASK_BITS:
        return None
    modulus = max(1 << 16, min(MASK_BITS, n * BITS_AN_ID)) | 1
    place = F.pmod("id", F.lit(modulus)) + 1
    rows = ids.groupBy(F.bitmap_bucket_number(place).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(place)).alias("bits")).collect()
    out = bytearray((modulus // 32768 + 1) * 4096)
    for r in rows:
        out[(r["bucket"] - 1) * 4096 : r["bucket"] * 4096] = r["bits"]
    return modulus, bytes(out)


def _sets(shingle: int, mask: tuple[int, bytes] | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        bits = mask and np.unpackbits(np.frombuffer(mask[1], np.uint8), bitorder="little").astype(bool)

        def work(part: pa.RecordBatch) -> pa.RecordBatch:
            grams = [shingle_set(text_words(t), shingle, hashes).view(np.int64) for t in part.column("text").to_pylist()]
            return pa.RecordBatch.from_arrays([part.column("id"), list_array(grams, pa.int64())], ["id", "grams"])

        for batch in batches:
            if mask:
                batch = batch.filter(pa.array(bits[batch.column("id").to_numpy() % mask[0]]))
            yield from map(work, slices(batch))
        hashes.clear()
        give_back()

    return run


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Edges (u, v) of the pairs (a, b) whose full sets reach the similarity."""
    left, right = sets.select(F.col("id").alias("a"), F.col("grams").alias("ga")), sets.select(F.col("id").alias("b"), F.col("grams").alias("gb"))
    both = F.size(F.array_intersect("ga", "gb"))
    j = pairs.join(left, "a").join(right, "b")
    return j.where(100 * both >= percent * (F.size("ga") + F.size("gb") - both)).select(F.col("a").alias("u"), F.col("b").alias("v"))


def _distinct_buckets(members: DataFrame) -> DataFrame:
    """Keys of buckets with two members or more; one key for each member set (told by its size and two xor-ed hashes)."""
    print_of = members.groupBy("key").agg(F.min("rep").alias("lo"), F.max("rep").alias("hi"), F.count("*").alias("m"), F.bit_xor(F.xxhash64("rep")).alias("x"), F.bit_xor(F.xxhash64("rep", F.lit(7))).alias("y"))
    return print_of.where("lo < hi").groupBy("lo", "hi", "m", "x", "y").agg(F.min("key").alias("key")).select("key")


def links_in_block(comps: np.ndarray, grams: list[np.ndarray], blocks: np.ndarray, percent: int) -> list[tuple[int, int]]:
    """A spanning forest, over components, of the links between members of different components.

    `blocks`: the members' block; with two blocks only pairs across them count, as each block also meets itself.
    """
    sizes = np.array([len(g) for g in grams])
    owner = np.repeat(np.arange(len(grams)), sizes)
    _, column = np.unique(np.concatenate(grams), return_inverse=True)
    order = np.argsort(column, kind="stable")
    begin = np.concatenate(([0], np.cumsum(np.bincount(column))))
    posting, first = owner[order], np.concatenate(([0], np.cumsum(sizes)))
    names, counts = np.unique(comps, return_counts=True)
    root = {c: c for c in names.tolist()}

    def find(c):
        while root[c] != c:
            root[c] = c = root[root[c]]
        return c

    out, across = [], len(np.unique(blocks)) > 1
    # the largest component's members need not ask: the others ask them
    for i in np.flatnonzero(comps != names[counts.argmax()]).tolist():
        columns = column[first[i] : first[i + 1]]
        length = begin[columns + 1] - begin[columns]
        at = np.repeat(begin[columns] - (np.cumsum(length) - length), length) + np.arange(length.sum())
        both = np.bincount(posting[at], minlength=len(grams))
        hit = (100 * both >= percent * (sizes[i] + sizes - both)) & (comps != comps[i])
        if across:
            hit &= blocks != blocks[i]
        for c in np.unique(comps[hit]).tolist():
            u, v = find(int(comps[i])), find(c)
            if u != v:
                root[max(u, v)] = min(u, v)
                out.append((int(comps[i]), c))
    return out


def _block_links(rest: DataFrame, sets: DataFrame, percent: int, block: int = 512, shingles: int = 1 << 19) -> DataFrame:
    """Edges (u, v) between components from all pairs inside the buckets of `rest` (key, rep, comp, m, w), by pairs of blocks.

    A bucket of m members with w shingles in all is dealt to as many blocks as keep one to about `block` members and `shingles` shingles.
    """
    count = F.greatest(F.ceil(F.col("m") / block), F.ceil(F.col("w") / shingles), F.lit(1)).cast("int")
    dealt = rest.withColumn("blocks", count).withColumn("own", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    filled = dealt.join(sets.withColumnRenamed("id", "rep"), "rep")
    met = filled.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = met.select("key", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), "own", "comp", "grams")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held = None, []

        def flush() -> pa.RecordBatch:
            comps, blocks, grams = (list(x) for x in zip(*held, strict=True))
            links = links_in_block(np.array(comps), grams, np.array(blocks), percent) if len(set(comps)) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([x[i] for x in links], pa.int64()) for i in range(2)], ["u", "v"])

        for batch in batches:
            grams = batch.column("grams")
            ends, values = grams.offsets.to_numpy(), grams.values.to_numpy()
            places = zip(*[batch.column(c).to_pylist() for c in ("key", "lo", "hi")], strict=True)
            for i, (place, comp, own) in enumerate(zip(places, batch.column("comp").to_pylist(), batch.column("own").to_pylist(), strict=True)):
                if place != at:
                    if held:
                        yield flush()
                    at, held = place, []
                held.append((comp, own, values[ends[i] : ends[i + 1]]))
        if held:
            yield flush()
        held = []
        give_back()

    return rows.repartition("key", "lo", "hi").sortWithinPartitions("key", "lo", "hi").mapInArrow(run, "u long, v long")


def _linkable(members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Members that can link at all: a document whose share of shingles that no other candidate has is over 1 - percent / 100 cannot.

    Exact: a partner is a candidate too, so the intersection is at most the shared shingles, and the union at least the whole set. Shingles
    are counted with map-side combine; one that a single document has names that document, so nothing is joined back.
    """
    grams = sets.select("id", F.explode("grams").alias("gram")).groupBy("gram").agg(F.count("*").alias("df"), F.min("id").alias("id"))
    own = grams.where("df = 1").groupBy(F.col("id").alias("_id")).agg(F.count("*").alias("own"))
    able = members.join(own, F.col("rep") == F.col("_id"), "left").where(100 * (F.col("n") - F.coalesce("own", F.lit(0))) >= percent * F.col("n"))
    alive = _distinct_buckets(able)
    kept = materialize(able.join(alive, "key").select("key", "rep", "n", "comp"), "members")
    discard(members)
    return kept


def near_duplicate_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, percent: int = 80, bands: int = 32, rows: int = 4) -> DataFrame:
    """One row per document: id, n_shingles, component_id (least id reachable), kept (id = component_id).

    Documents link if 100 * |intersection| >= percent * |union| of their shingle sets. Null or wordless texts are
    linked with nothing. Rows with a null id get a null component and are not kept; rows that repeat an id are
    one document; if their texts differ, links are confirmed on one of their sets, the greatest in array order. An empty table gives no rows. A very long text costs its words and
    8 bytes a shingle, nothing else grows with it. Extra columns are ignored, whatever their names.
    """
    plain = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    sketch = materialize(plain.mapInArrow(_sketches(shingle, bands * rows, bands), "id long, n long, set_a long, set_b long, keys array<long>"), "sketch")
    linked = sketch.where("n > 0 AND id IS NOT NULL")
    # one document for each distinct set; copies are combined before the shuffle. As a table it is computed once, and the last join
    # reads both sides from plain exchanges, which the adaptive planner can split where one set has very many copies
    reps = materialize(linked.groupBy("set_a", "set_b").agg(F.min("id").alias("rep")), "reps")
    # the id is among the join keys, so that copies of one text do not meet in one task
    heads = linked.join(reps.withColumnRenamed("rep", "id"), ["id", "set_a", "set_b"]).select(F.col("id").alias("rep"), "n", F.explode("keys").alias("key"))
    shared = _distinct_buckets(heads)
    members = materialize(heads.join(shared, "key").distinct().withColumn("comp", F.col("rep")), "members")
    wanted = members.select(F.col("rep").alias("id")).distinct()
    mask = _id_mask(wanted)
    texts = plain.where("id IS NOT NULL") if mask else plain.join(wanted, "id", "left_semi")
    sets = materialize(texts.mapInArrow(_sets(shingle, mask), "id long, grams array<long>"), "sets")
    sets_once = sets.groupBy("id").agg(F.max("grams").alias("grams")) if not sets.groupBy("id").count().where("count > 1").isEmpty() else sets
    members = _linkable(members, sets_once, percent)
    # a table, as are `rest` and its open keys: a join right above an aggregate by the same key could not be split at a hot bucket
    pivots = materialize(members.groupBy("key").agg(F.min(F.struct("rep", "n", "comp")).alias("p")).select("key", F.col("p.rep").alias("p_rep"), F.col("p.n").alias("p_n")), "pivots")
    near = (F.least("n", "p_n") * 100 >= F.greatest("n", "p_n") * percent) & (F.col("rep") > F.col("p_rep"))
    pairs = members.join(pivots, "key").where(near).select(F.col("rep").alias("a"), F.col("p_rep").alias("b")).distinct()
    labels = connected_components(_verified(pairs, sets_once, percent))
    # the least member has met all others; what is left of a bucket matters while it spans components
    rest = members.join(pivots.select("key", "p_rep"), "key").where("rep > p_rep").drop("p_rep")
    if labels is not None:
        rest = relabel(rest, "comp", labels)
    left_over = materialize(rest.select("key", "rep", "comp", "n"), "rest")
    bounds = left_over.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("m"), F.sum("n").alias("w"))
    open_keys = materialize(bounds.where("lo < hi").select("key", "m", "w"), "open")
    rest = materialize(left_over.join(open_keys, "key").select("key", "rep", "comp", "m", "w"), "rest")
    discard(pivots, left_over, open_keys)
    merged = connected_components(_block_links(rest, sets_once, percent))
    if merged is not None:
        older, step = labels, merged.select("node", "root")
        labels = merged if older is None else materialize(relabel(older.select("node", "root"), "root", step).unionByName(step), "labels")
        discard(older)
    discard(members, rest, sets)
    reps = reps.withColumn("comp", F.col("rep"))
    if labels is not None:
        reps = relabel(reps, "comp", labels)
    out = sketch.select("id", "n", "set_a", "set_b").join(reps, ["set_a", "set_b"], "left")
    component = F.when(F.col("id").isNotNull(), F.coalesce("comp", "id"))
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(component == F.col("id"), F.lit(False)).alias("kept"))
