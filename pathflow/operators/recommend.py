"""Recommendation as walks: content, collaborative, hybrid.

The walks and their multiplicities are the method; normalisation, novelty and hybrid formulas are textbook forms of our own choice, as the
method only names these aims.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.lower import run
from ..plans.traversal import HERE, Walk
from ..sources.dictionary import global_rank
from ..sources.graph import PropertyGraph
from ..sources.scratch import shuffles_freed, stored


def content_neighbors(label: str = "feature", exclude_all: Iterable[int] = ()) -> Walk:
    """Resources that share features: as often as features are shared. Each start is removed from its own walk; exclude_all removes a whole set."""
    walk = HERE.mark("resource").out(label).into(label).drop_marked("resource")
    ids = tuple(exclude_all)
    return walk.drop_element(ids) if ids else walk


def liked(label: str = "likes") -> Walk:
    return HERE.out(label)


def similar_people(label: str = "likes") -> Walk:
    """People with common likes: as often as likes are shared."""
    return HERE.mark("person").out(label).into(label).drop_marked("person")


def collaborative(label: str = "likes") -> Walk:
    """What similar people like, weighted by shared likes."""
    return similar_people(label) >> liked(label)


def content_by_likes(likes: str = "likes", feature: str = "feature") -> Walk:
    return liked(likes) >> content_neighbors(feature)


def friend_of_friend(label: str = "friend") -> Walk:
    return HERE.out(label).out(label)


def foaf(graph: PropertyGraph, spark: SparkSession, ids: list[int], label: str = "friend", exclude_self: bool = False, exclude_direct: bool = False) -> DataFrame:
    """Two friend steps; the exclusions are options beyond the two steps."""
    walk = friend_of_friend(label)
    if exclude_self:
        walk = HERE.mark("me") >> walk.drop_marked("me")
    out = run(graph, spark, walk, ids)
    if exclude_direct:
        direct = run(graph, spark, HERE.out(label), ids).select(F.col("pos").alias("_d"))
        out = out.join(direct, out.pos == F.col("_d"), "left_anti")
    return out


#: The library of named sub-walks.
LIBRARY = {"content": content_neighbors(), "liked": liked(), "similar": similar_people(), "collaborative": collaborative(), "content_by_likes": content_by_likes(), "foaf": friend_of_friend()}


def recommend_unknown(graph: PropertyGraph, spark: SparkSession, walk: Walk, ids: list[int] | None = None, frame: DataFrame | None = None, label: str = "likes") -> DataFrame:
    """The walk's resources that its origin does not know yet (anti join on origin and resource)."""
    out = run(graph, spark, walk, ids, frame, per_origin=True)
    known = run(graph, spark, liked(label), ids, frame, per_origin=True).select("origin", "pos")
    return out.join(known, ["origin", "pos"], "left_anti")


def by_overlap(graph: PropertyGraph, spark: SparkSession, ids: list[int], min_shared: int = 0, min_ratio: float = 0.0, label: str = "likes") -> DataFrame:
    """Collaborative recommendation through people who share enough: a count, or a share of the origin's own likes."""
    people = run(graph, spark, similar_people(label), ids, per_origin=True)
    own = run(graph, spark, liked(label), ids, per_origin=True).groupBy("origin").agg(F.count("*").alias("own"))
    people = people.join(own, "origin").where((F.col("weight") >= min_shared) & (F.col("weight") >= F.col("own") * min_ratio))
    return run(graph, spark, liked(label), frame=people.select("pos", "weight"))


def content_scores(graph: PropertyGraph, spark: SparkSession, ids: list[int], normalize: str = "none", novelty: str = "none", max_degree: int | None = None, label: str = "feature") -> DataFrame:
    """(pos, shared, score) of content neighbours.

    normalize: none, feature (1 / in-degree at the feature), resource (1 / out-degree at the far resource), both, cosine, jaccard.
    novelty: none, idf (ln((N + 1) / (degree + 1)) at the feature), max_degree (only features of at most that degree).
    """
    if normalize not in ("none", "feature", "resource", "both", "cosine", "jaccard") or novelty not in ("none", "idf", "max_degree"):
        raise ValueError(f"normalize={normalize}, novelty={novelty}")
    e = graph.edges(label).select("src", "dst")
    into = e.groupBy("dst").agg(F.count("*").alias("f_deg"))
    outof = e.groupBy("src").agg(F.count("*").alias("r_deg"))
    first = e.where(F.col("src").isin(*ids)).select(F.col("src").alias("start"), "dst").join(into, "dst")
    factor = F.lit(1.0)
    if normalize in ("feature", "both"):
        factor = factor / F.col("f_deg")
    if novelty == "idf":
        n = outof.agg(F.count("*").alias("n"))
        first = first.crossJoin(F.broadcast(n))  # one row
        factor = factor * F.ln((F.col("n") + 1) / (F.col("f_deg") + 1))
    if novelty == "max_degree":
        first = first.where(F.col("f_deg") <= max_degree)
    back = first.withColumn("x", factor).join(e.withColumnRenamed("src", "pos"), "dst").where("pos <> start")
    pairs = back.groupBy("start", "pos").agg(F.count("*").alias("shared"), F.sum("x").alias("score"))
    if normalize in ("resource", "both"):
        pairs = pairs.join(outof, pairs.pos == outof.src).withColumn("score", F.col("score") / F.col("r_deg"))
    elif normalize in ("cosine", "jaccard"):
        mine = outof.select(F.col("src").alias("start"), F.col("r_deg").alias("a"))
        pairs = pairs.join(mine, "start").join(outof.select(F.col("src").alias("pos"), F.col("r_deg").alias("b")), "pos")
        size = F.sqrt(F.col("a") * F.col("b")) if normalize == "cosine" else F.col("a") + F.col("b") - F.col("shared")
        pairs = pairs.withColumn("score", F.col("score") / size)
    return pairs.groupBy("pos").agg(F.sum("shared").alias("shared"), F.sum("score").alias("score"))


def hybrid(walks: list[tuple[DataFrame, float]], how: str = "sum") -> DataFrame:
    """Combine results (pos, weight) of several walks: (pos, score).

    sum: coefficient * weight / greatest weight. rank: coefficient / (60 + rank). gate: the first result where the others reach it too.
    """
    if how == "gate":
        out = walks[0][0]
        for other, _ in walks[1:]:
            out = out.join(other.select("pos"), "pos", "left_semi")
        return out.select("pos", F.col("weight").cast("double").alias("score"))
    parts = None
    for df, coefficient in walks:
        if how == "sum":
            top = df.agg(F.max("weight").alias("top"))  # one row
            one = df.crossJoin(F.broadcast(top)).select("pos", (F.lit(float(coefficient)) * F.col("weight") / F.col("top")).alias("score"))
        elif how == "rank":
            ranked = global_rank(df.select("pos", "weight"), [F.desc("weight"), F.asc("pos")], "r")
            one = ranked.select("pos", (F.lit(float(coefficient)) / (61 + F.col("r"))).alias("score"))
        else:
            raise ValueError(how)
        parts = one if parts is None else parts.unionByName(one)
    return parts.groupBy("pos").agg(F.sum("score").alias("score"))


def shared_pairs(edges: DataFrame, resource: str = "dst", person: str = "src", weight: str | None = None, origins: DataFrame | None = None, block: int = 4096) -> DataFrame:
    """(a, b, weight) of all ordered pairs with a common resource: the batch form, a self-join on the resource.

    The edges of a resource of degree d are dealt, by hash of the person, to ceil(d / block) blocks, and each pair of blocks is a join key of its own, so that no task
    gets more than block * block pairs of one hub. With `weight`, parallel edges count as products. origins (one column): only their pairs, (a, b) with a among them.
    """
    e = edges.select(F.col(person).alias("p"), F.col(resource).alias("r"), (F.col(weight) if weight else F.lit(1)).cast("long").alias("w"))
    hubs = e.groupBy("r").agg(F.count("*").alias("d")).where(F.col("d") > block).select(F.col("r").alias("h"), F.ceil(F.col("d") / block).cast("int").alias("n"))
    dealt = e.join(hubs, e.r == hubs.h, "left").select("p", "r", "w", F.coalesce("n", F.lit(1)).alias("n"))
    own, other = F.pmod(F.xxhash64("p"), F.col("n")).cast("int"), F.explode(F.sequence(F.lit(0), F.col("n") - 1))
    left = dealt.select("r", F.col("p").alias("a"), F.col("w").alias("wa"), own.alias("i"), other.alias("j"))
    right = dealt.select("r", F.col("p").alias("b"), F.col("w").alias("wb"), own.alias("j"), other.alias("i"))
    if origins is not None:
        left = left.join(origins.select(F.col(origins.columns[0]).alias("o")), F.col("a") == F.col("o"), "left_semi")
    return left.join(right, ["r", "i", "j"]).where("a <> b").groupBy("a", "b").agg(F.sum(F.col("wa") * F.col("wb")).alias("weight"))


#: Stands for a null resource inside a task: after all others, as in the order of the result.
_NULL = (1 << 63) - 1


def _gathered(starts: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of the members of the lists `which`, one list after the other, and the lists' lengths."""
    lengths = starts[which + 1] - starts[which]
    return np.arange(lengths.sum()) + np.repeat(starts[which] - (np.cumsum(lengths) - lengths), lengths), lengths


def _block(batches: list[pa.RecordBatch], width: int) -> tuple[np.ndarray, ...]:
    """The likes of a block's people: resources in order; their codes in rows of `width`, filled up with the number of resources; each person's first row; who likes a code, and the codes' first places there."""
    degree = np.concatenate([b.column("resources").value_lengths().to_numpy() for b in batches]).astype(np.int64)
    coded = pa.chunked_array([b.column("resources").flatten() for b in batches]).dictionary_encode().unify_dictionaries()
    batches.clear()  # the codes take half the room
    values = coded.chunk(0).dictionary.to_numpy()
    order = np.argsort(values)
    place = np.empty(len(values), np.int32)
    place[order] = np.arange(len(values), dtype=np.int32)
    counts = np.zeros(len(values), np.int64)
    for c in coded.chunks:
        counts += np.bincount(c.indices.to_numpy(), minlength=len(values))
    into = np.concatenate(([0], np.cumsum(counts[order])))
    row = np.concatenate(([0], np.cumsum(-(-degree // width))))
    likes = np.concatenate(([0], np.cumsum(degree)))
    grid = np.full((row[-1], width), len(values), np.int32)
    flat, who, free, at = grid.reshape(-1), np.empty(likes[-1], np.int32), into[:-1].copy(), 0
    for c in coded.chunks:
        code = place[c.indices.to_numpy()]
        i = np.arange(at, at + len(code))
        at += len(code)
        person = np.searchsorted(likes, i, "right") - 1
        flat[row[person] * width + i - likes[person]] = code
        key = np.sort(code.astype(np.int64) << 32 | person)
        code = key >> 32
        first = np.flatnonzero(np.diff(code, prepend=-1))
        lengths = np.diff(first, append=len(code))
        who[free[code] + np.arange(len(code)) - np.repeat(first, lengths)] = key & 0xFFFFFFFF
        free[code[first]] += lengths
    return values[order], grid, row, who, into


def _best(batches: Iterable[pa.RecordBatch], k: int, piece: int = 1 << 22, width: int = 8, flush: int = 4096) -> Iterator[pa.RecordBatch]:
    """The k best resources of each own person of a block, from the likes of all whom the block reaches; sums by one person at a time, in steps of about `piece` likes."""
    given = [b for b in batches if b.num_rows]
    if not given:
        return
    person = np.concatenate([b.column("person").to_numpy() for b in given])
    own = np.flatnonzero(np.concatenate([b.column("own").to_numpy(zero_copy_only=False) for b in given]))
    resources, grid, row, who, into = _block(given, width)
    size, flat = len(resources), grid.reshape(-1)
    known = size - int(resources[-1] == _NULL)  # null meets nothing, but may be met
    weight = np.zeros(size + 1, np.int64)  # the last is of what fills up rows
    found: list[tuple[np.ndarray, ...]] = []

    def batch() -> pa.RecordBatch:
        me, top, sums, rank = (np.concatenate(x) for x in zip(*found, strict=True))
        found.clear()
        pos = pa.array(resources[top], pa.int64(), mask=resources[top] == _NULL)
        return pa.RecordBatch.from_arrays([pa.array(person[me]), pos, pa.array(sums), pa.array(rank)], ["origin", "pos", "weight", "rank"])

    for me in own:
        mine = flat[row[me] * width : row[me + 1] * width]
        people, shared = np.unique(who[_gathered(into, mine[mine < known])[0]], return_counts=True)
        others = people != me
        people, shared = people[others], shared[others]
        if not len(people):
            continue
        ends, at = np.cumsum(row[people + 1] - row[people]), 0
        while at < len(people):
            stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + piece // width, "right")))
            met = grid.take(_gathered(row, people[at:stop])[0], axis=0).reshape(-1)
            np.add.at(weight, met, 1)
            more = at + np.flatnonzero(shared[at:stop] > 1)
            if len(more):
                places, lengths = _gathered(row, people[more])
                np.add.at(weight, grid.take(places, axis=0).reshape(-1), np.repeat(shared[more] - 1, lengths * width))
            few = at == 0 and stop == len(people) and 2 * len(met) < size
            at = stop
        weight[size] = 0
        # k of one's own resources have at least that weight, so the best have it too
        liked = np.unique(mine)
        least = max(1, np.partition(weight[liked], -k)[-k]) if k <= len(liked) else 1
        top = np.unique(met[weight[met] >= least]) if few else np.flatnonzero(weight >= least)
        if k < len(top):
            top = top[weight[top] >= np.partition(weight[top], -k)[-k]]
        top = top[np.argsort(-weight[top], kind="stable")[:k]]
        found.append((np.full(len(top), me), top, weight[top], np.arange(1, len(top) + 1, dtype=np.int32)))
        weight[met if few else slice(None)] = 0
        if len(found) == flush:
            yield batch()
    if found:
        yield batch()


def best_of_each(edges: DataFrame, k: int, paths: int = 1_000_000_000, copies: int | None = None) -> DataFrame:
    """(origin, pos, weight, rank): the walk `collaborative().rank(k)` from every person at once; equal weights by resource, a null one last.

    People are dealt to ranges of about `paths` paths each. A task gets the likes of all whom its range reaches, once, and sums one person's paths in
    an array of resources, so neither paths nor (person, resource) pairs cross the network. A task holds those likes; there is no cap.
    Which ranges reach a person is found by sets of ranges as bits, over resources and back, so no (range, person) pair is shuffled before its likes are. Ranges go in waves that hold
    `copies` copies of all likes at most (as many as there are cores, where it is not given) or one range; a wave's shuffle goes when its result is stored.
    """
    spark = edges.sparkSession
    e = edges.where("src IS NOT NULL").select("src", "dst")
    people = stored(e.groupBy("src").agg(F.collect_list(F.coalesce("dst", F.lit(_NULL))).alias("resources")), "people")
    parallel = spark.sparkContext.defaultParallelism
    with shuffles_freed(spark):
        liked = people.select(F.size("resources").cast("long").alias("o"), F.explode("resources").alias("dst")).where(F.col("dst") != _NULL)
        total = liked.groupBy("dst").agg(F.count("*").alias("i"), F.sum("o").alias("o")).agg(F.sum(F.col("i") * F.col("o"))).first()[0] or 0
        n = max(2 * parallel, -(-int(total) // paths))
        bounds = sorted({int(x) for x in e.approxQuantile("src", [i / n for i in range(1, n)], 0.1 / n)}) if total else []
        below = [F.lit(0), *[(F.lit(b) < F.col("src")).cast("int") for b in bounds]]
        while len(below) > 1:  # a balanced sum, so that many ranges make no deep expression
            below = [reduce(Column.__add__, below[i : i + 8]) for i in range(0, len(below), 8)]
        people, n = people.withColumn("home", below[0]), len(bounds) + 1
        words = [f"m{i}" for i in range(-(-n // 64))]
        met = people.select("src", "home", F.explode("resources").alias("dst")).where(F.col("dst") != _NULL)
        bits = [F.bit_or(F.expr(f"if(home div 64 = {i}, shiftleft(1L, home % 64), 0L)")).alias(w) for i, w in enumerate(words)]
        reached = met.select("src", "dst").join(met.groupBy("dst").agg(*bits), "dst").groupBy("src").agg(*[F.bit_or(w).alias(w) for w in words])
        held = stored(people.join(reached, "src").select("src", "resources", "home", F.array(*words).alias("blocks")), "reached")

        def block(first: int, last: int) -> Column:
            return F.expr(f"explode(filter(sequence({first}, {last}), b -> getbit(blocks[cast(b div 64 AS INT)], b % 64) = 1))").alias("block")

        sizes = held.select(block(0, n - 1), F.size("resources").cast("long").alias("o")).groupBy("block").agg(F.sum("o")).collect()
        likes = held.agg(F.sum(F.size("resources").cast("long"))).first()[0] or 0
    waves, room = [], 0
    for b, o in sorted(map(tuple, sizes)):
        if not waves or o > room:
            waves.append([b, b])
            room = (copies or parallel) * likes
        waves[-1][1] = b
        room -= o

    def best(first: int, last: int) -> DataFrame:
        given = held.select(block(first, last), F.col("src").alias("person"), "resources", "home").withColumn("own", F.col("home") == F.col("block")).drop("home")
        dealt = given.repartitionById(last - first + 1, F.col("block") - first)
        return dealt.mapInArrow(lambda batches: _best(batches, k), "origin long, pos long, weight long, rank int")

    if len(waves) < 2:
        return best(*(waves[0] if waves else (0, 0)))
    return reduce(DataFrame.unionByName, [stored(best(*w), "best") for w in waves])


def signature_quotient(edges: DataFrame) -> DataFrame:
    """(a, b, weight) as `shared_pairs` for resources that fall into few feature signatures.

    Resources with one feature set have equal shares with all others, so shares are computed between signatures and expanded by members;
    only a resource's pairing with itself is dropped. It pays where signatures are far fewer than resources; the caller decides by counts.
    """
    sig = edges.groupBy("src").agg(F.sort_array(F.collect_set("dst")).alias("features"))
    sig = sig.withColumn("sig", F.struct(F.xxhash64("features"), "features"))  # the list itself decides, its hash deals
    kinds = sig.select("sig").distinct().select("sig", F.explode("sig.features").alias("dst"))
    left, right = kinds.select("dst", F.col("sig").alias("sa")), kinds.select("dst", F.col("sig").alias("sb"))
    shares = left.join(right, "dst").groupBy("sa", "sb").agg(F.count("*").alias("weight"))
    members = sig.select("src", "sig")
    a = members.select(F.col("src").alias("a"), F.col("sig").alias("sa"))
    b = members.select(F.col("src").alias("b"), F.col("sig").alias("sb"))
    return shares.join(a, "sa").join(b, "sb").where("a <> b").select("a", "b", "weight")


def signature_totals(edges: DataFrame, subsets_of: int = 8) -> DataFrame:
    """(a, neighbours, shares): how many others share a feature with each resource, and how often in sum, as `signature_quotient` would expand to.

    No pair of resources or signatures is made: resources that hold all of a feature set are counted for every subset of a signature, and those that share
    a feature with it are the alternating sum of its subsets' counts (inclusion and exclusion). Subsets double with every feature, so signatures of more than `subsets_of`
    features meet all others by a join. A resource's pairing with itself is taken off, and resources without neighbours have no row.
    """
    sig = edges.where("dst IS NOT NULL").groupBy("src").agg(F.sort_array(F.collect_set("dst")).alias("features"))
    kinds = sig.groupBy("features").agg(F.count("*").alias("members")).withColumn("sig", F.struct(F.xxhash64("features"), "features"))  # the list itself decides, its hash deals
    few = kinds.where(F.size("features") <= subsets_of)
    # subsets by bit mask over the signature's own features, the empty one left out
    masked = few.select("sig", "members", "features", F.expr("explode(sequence(1, shiftleft(1, size(features)) - 1))").alias("mask"))
    subset = F.expr("filter(features, (_, i) -> shiftright(mask, i) % 2 = 1)")
    subsets = masked.select("sig", "members", subset.alias("subset")).withColumn("subset", F.struct(F.xxhash64("subset"), "subset"))
    held = subsets.groupBy("subset").agg(F.sum("members").alias("n"))
    size = F.size("subset.subset")
    counted = subsets.select("sig", "subset").join(held, "subset").groupBy("sig").agg(
        F.sum(F.when(size % 2 == 1, F.col("n")).otherwise(-F.col("n"))).alias("met"), F.sum(F.when(size == 1, F.col("n")).otherwise(0)).alias("shared")
    )
    each = kinds.select("sig", "members", (F.size("features") > subsets_of).alias("many"), F.explode("features").alias("dst"))
    far = each.select("dst", F.col("sig").alias("far"), "members", F.col("many").alias("far_many"))
    pairs = each.where("many").select("dst", "sig").join(far, "dst").unionByName(each.where("NOT many").select("dst", "sig").join(far.where("far_many"), "dst"), True)
    shares = pairs.groupBy("sig", "far").agg(F.count("*").alias("n"), F.first("members").alias("members"))
    joined = shares.groupBy("sig").agg(F.sum("members").alias("met"), F.sum(F.col("n") * F.col("members")).alias("shared"))
    totals = counted.unionByName(joined).groupBy("sig").agg(F.sum("met").alias("met"), F.sum("shared").alias("shared"))
    a = sig.select(F.col("src").alias("a"), F.struct(F.xxhash64("features"), "features").alias("sig"), F.size("features").alias("own"))
    return a.join(totals, "sig").select("a", (F.col("met") - 1).alias("neighbours"), (F.col("shared") - F.col("own")).alias("shares")).where("neighbours > 0")
