"""Queries that run over whole tables: no id range, filter or cap before the operator."""

import re
import time
from collections import Counter

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from pathflow.operators import recommend
from pathflow.operators.recommend import _NULL
from pathflow.plans.lower import run, run_in_batches
from pathflow.plans.traversal import HERE
from pathflow.sources.graph import EdgeLabel, PropertyGraph
from pathflow.sources.scratch import stored
from pathflow.workloads.queries import QUERIES

from .toys import graph

SF = "/root/testdata/sf0.001"


def table(spark, name):
    return spark.read.parquet(f"{SF}/{name}.parquet")


def test_every_event_takes_the_static_hop(spark):
    lines = table(spark, "lineitem").select("l_orderkey")
    liked = {r[0] for r in table(spark, "orders").join(lines, F.col("o_orderkey") == F.col("l_orderkey")).select("o_custkey").distinct().collect()}
    due = {r.event_id for r in table(spark, "events").collect() if r.user_id in liked}
    assert {r[0] for r in QUERIES["stream_static_hop"](spark, SF).select("event_id").distinct().collect()} == due


def test_every_customer_with_company_has_a_top_10(spark):
    pairs = QUERIES["virtual_copurchase"](spark, SF)
    people = {r[0] for r in pairs.select("a").distinct().collect()}
    nations = {r.c_custkey: r.c_nationkey for r in table(spark, "customer").collect()}
    assert len({nations[p] for p in people}) > 1 and max(people) > 50
    assert {r[0] for r in QUERIES["cf_top10_each"](spark, SF).select("customer").distinct().collect()} == people


def test_batches_of_origins_lose_none(spark):
    g = graph(spark, {"likes": [(p, r) for p in range(1, 21) for r in (100 + p, 101 + p)]})
    start = spark.createDataFrame([(p,) for p in range(1, 21)], "pos long")
    walk = recommend.collaborative().rank(2)
    whole = run(g, spark, walk, frame=start, per_origin=True)
    batches = run_in_batches(g, spark, walk, start, 10)
    assert {tuple(r) for r in batches.collect()} == {tuple(r) for r in whole.collect()} and len(batches.inputFiles()) > 1
    assert run_in_batches(g, spark, walk, start.limit(0), 10).count() == 0


def test_surface_queries_take_every_part_and_customer(spark):
    parts = {r.p_partkey for r in table(spark, "part").collect()}
    for name in ("join_lateral_features", "udtf_words"):
        assert {r.part for r in QUERIES[name](spark, SF).collect()} == parts
    likes = QUERIES["agg_distinct"](spark, SF).groupBy().sum("people").first()[0]
    paths = QUERIES["udtf_paths"](spark, SF)
    assert paths.count() == likes and paths.where("customer >= 20").count() > 0
    assert {r.edges for r in QUERIES["scan_formats_roundtrip"](spark, SF).collect()} == {likes}


def test_signature_totals_are_those_of_all_pairs(spark):
    g = graph(spark, {"feature": [(1, 10), (1, 11), (2, 10), (2, 11), (3, 11), (3, 12), (4, 13), (30, 10), (31, 12)]})
    e = g.edges("feature")
    pairs = recommend.shared_pairs(e).groupBy("a").agg(F.count("*").alias("neighbours"), F.sum("weight").alias("shares"))
    assert {tuple(r) for r in recommend.signature_totals(e).collect()} == {tuple(r) for r in pairs.collect()} == {(1, 3, 4), (2, 3, 4), (3, 3, 3), (30, 2, 2), (31, 1, 1)}


@pytest.mark.parametrize("paths", [1, 10**9])
def test_best_of_each_is_the_ranked_walk(spark, paths):
    """Ties, parallel edges, people without company and fewer resources than asked for; a null resource meets nobody but is met."""
    likes = [(p, 100 + r) for p in range(1, 31) for r in range(9) if (p * 5 + r * r) % 7 < 3] + [(3, 101), (3, 101), (50, 200)]
    g = graph(spark, {"likes": likes})
    e = g.edges("likes")
    due = run(g, spark, recommend.collaborative().rank(4), frame=e.select(F.col("src").alias("pos")).distinct(), per_origin=True).select("origin", "pos", "weight", "rank")
    due = {tuple(r) for r in due.collect()}
    assert {tuple(r) for r in recommend.best_of_each(e, 4, paths).collect()} == due and len({r[0] for r in due}) == 30
    assert recommend.best_of_each(e.where("src < 0"), 4, paths).count() == 0
    odd = spark.createDataFrame([(1, 5), (2, 5), (2, None), (3, None), (None, 5)], "src long, dst long")
    assert {tuple(r) for r in recommend.best_of_each(odd, 4, paths).collect()} == {(1, 5, 1, 1), (1, None, 1, 2), (2, 5, 1, 1)}


def shuffle_files(spark):
    """Shuffle files on disk, once those on their way out are gone."""
    files, seen = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager(), -1
    for _ in range(20):
        found = files.getAllFiles()
        n = sum(found.apply(i).getName().startswith("shuffle_") for i in range(found.size()))
        if n == seen:
            return n
        seen = n
        time.sleep(1)
    return seen


@pytest.mark.parametrize("copies", [1, None])
def test_best_of_each_keeps_little_on_disk(spark, copies):
    """Every range reaches everybody. Ranges in waves give the ranked walk too; shuffles of layouts and waves are gone afterwards."""
    e = spark.createDataFrame([(p, p * p * r % 23) for p in range(1, 41) for r in range(1, 8)], "src long, dst long").distinct().localCheckpoint()
    due = run(PropertyGraph.of([], [EdgeLabel("likes", lambda: e.select(F.lit(0).alias("eid"), "src", "dst"))]), spark, recommend.collaborative().rank(4), frame=e.select(F.col("src").alias("pos")).distinct(), per_origin=True)
    due = {tuple(r) for r in due.select("origin", "pos", "weight", "rank").collect()}
    before = shuffle_files(spark)
    found = stored(recommend.best_of_each(e, 4, copies=copies), "found")
    assert shuffle_files(spark) <= before
    assert {tuple(r) for r in found.collect()} == due and len({r[0] for r in due}) > 30


def test_best_is_the_same_in_small_steps():
    """A block in many batches, hubs and few others: rows of any width, steps of any size."""
    likes = [sorted({(p * 7 + r * r) % 31 for r in range(2 + p % 9)}) for p in range(60)] + [list(range(31)), [100], [_NULL, 3]]
    schema = pa.schema([("person", pa.int64()), ("resources", pa.list_(pa.int64())), ("own", pa.bool_())])
    rows = [{"person": 1000 + p, "resources": x, "own": p % 2 == 0} for p, x in enumerate(likes)]
    due = set()
    for a, x in enumerate(likes):
        total = Counter()
        for b, y in enumerate(likes):
            for r in y if a != b and a % 2 == 0 else ():
                total[r] += len(set(x) & set(y) - {_NULL})
        best = sorted(((r, w) for r, w in total.items() if w), key=lambda t: (-t[1], t[0]))[:5]
        due |= {(1000 + a, None if r == _NULL else r, w, i + 1) for i, (r, w) in enumerate(best)}
    for piece, width, flush in [(1, 1, 1), (16, 8, 3), (1 << 22, 3, 4096)]:
        batches = [b for i in range(0, len(rows), 7) for b in pa.Table.from_pylist(rows[i : i + 7], schema).to_batches()]
        assert {(r["origin"], r["pos"], r["weight"], r["rank"]) for b in recommend._best(batches, 5, piece, width, flush) for r in b.to_pylist()} == due


@pytest.mark.parametrize("subsets_of", [0, 1, 2, 8])
def test_signature_totals_by_subsets_and_by_pairs(spark, subsets_of):
    """Signatures are few or many by size: both ways, and pairs of one with the other, give what all pairs give; members of a signature repeat."""
    likes = [(p, f) for p in range(1, 41) for f in range(5) if (p * 7 + 3) >> f & 1] + [(90, 77)]
    e = graph(spark, {"feature": likes}).edges("feature")
    sizes = {sum(q == p for q, _ in likes) for p, _ in likes}
    assert len(sizes) > 3
    pairs = recommend.shared_pairs(e).groupBy("a").agg(F.count("*").alias("neighbours"), F.sum("weight").alias("shares"))
    assert {tuple(r) for r in recommend.signature_totals(e, subsets_of).collect()} == {tuple(r) for r in pairs.collect()}


def test_a_word_in_many_documents_counts(spark):
    """Brute force over all words of document 1, also those in more than 50 documents."""
    words = {r.doc_id: set(re.findall(r"[^\W\d_]+", r.text.lower())) for r in table(spark, "documents").collect()}
    mine = words.pop(1)
    due = {d: len(mine & w) for d, w in words.items() if mine & w}
    assert max(sum(x in w for w in words.values()) for x in mine) > 50
    assert {r.doc: r.shared for r in QUERIES["cooc_documents"](spark, SF).collect()} == due


def test_each_walker_takes_one_edge_in(spark):
    g = graph(spark, {"likes": [(p, 100) for p in range(1, 41)]})
    start = spark.createDataFrame([(p,) for p in range(1, 41)], "pos long")
    ends = run(g, spark, HERE.sample_out("likes", 1, 1).sample_in("likes", 1, 2), frame=start, per_origin=True).collect()
    assert sorted(r.origin for r in ends) == list(range(1, 41)) and len({r.pos for r in ends}) > 10


def test_visits_add_up_to_the_walkers(spark):
    lines = table(spark, "lineitem").select("l_orderkey")
    walkers = table(spark, "orders").join(lines, F.col("o_orderkey") == F.col("l_orderkey")).select("o_custkey").distinct().count()
    assert QUERIES["random_walk_visits"](spark, SF).groupBy().sum("visits").first()[0] == walkers
