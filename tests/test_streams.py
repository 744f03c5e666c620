"""Custom state over several batches against brute force."""

from collections import Counter
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathflow.streaming import events as s

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("blocks", [1, 3])
def test_shared_counts_over_batches(spark, blocks):
    """Pairs within a batch and across batches, repeated edges, and edges without a person."""
    events = spark.read.parquet(f"{SF}/events.parquet").withColumn("user_id", F.when(F.col("event_id") % 7 > 0, F.col("user_id") % 5))
    parts = [lambda d, i=i: d.where(F.col("event_id") % 3 == i) for i in range(3)]
    stream = s.read_stream(spark, s.in_files(spark, events, parts), files_a_batch=1)
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    with s.rocksdb(spark):
        changes = s.drain(s.shared_changes(stream, ["event_type"], blocks))
    assert spark.conf.get("spark.sql.streaming.stateStore.providerClass") == before
    found = {(r.a, r.b): r.n for r in changes.groupBy("a", "b").agg(F.sum("shared").alias("n")).collect()}

    due, rows = Counter(), [(r.event_type, r.user_id) for r in events.collect() if r.user_id is not None]
    for (t, u), (other, v) in combinations(rows, 2):
        if t == other and u != v:
            due[min(u, v), max(u, v)] += 1
    assert found == due and len(due) == 10


@pytest.mark.parametrize("blocks, pairs", [(1, 10**9), (3, 5), (2, 300)])
def test_products_over_batches_add_up_to_pairs(spark, blocks, pairs):
    """Products of lists, cut into few and many ranges of people, give what brute force counts, each pair in one row; null people and resources are none."""
    odd = F.when(F.col("event_id") % 7 > 0, F.col("user_id") % 40 - 9), F.when(F.col("event_id") % 11 > 0, F.col("event_type"))
    events = spark.read.parquet(f"{SF}/events.parquet").withColumn("user_id", odd[0]).withColumn("event_type", odd[1]).where("event_id < 500")
    parts = [lambda d, i=i: d.where(F.col("event_id") % 3 == i) for i in range(3)]
    stream = s.read_stream(spark, s.in_files(spark, events, parts), files_a_batch=1)
    with s.rocksdb(spark):
        products = s.drain(s.shared_products(stream, ["event_type"], blocks))
    assert products.where("NOT ordered").count() > 0
    rows = [(r.event_type, r.user_id) for r in events.collect() if r.user_id is not None and r.event_type is not None]
    due = Counter()
    for (t, u), (other, v) in combinations(rows, 2):
        if t == other and u != v:
            due[min(u, v), max(u, v)] += 1
    assert sorted(tuple(r) for r in s.shared_totals(products, pairs).collect()) == sorted((*k, n) for k, n in due.items())
    assert s.shared_totals(products.limit(0), pairs).count() == 0


def test_the_sink_of_shared_counts_is_linear(spark):
    """What a batch stores grows with its edges, not with the pairs they make: 600 people at one place are 179,700 pairs."""
    crowd = spark.read.parquet(f"{SF}/events.parquet").where("event_id < 600").withColumn("user_id", F.col("event_id"))
    with s.rocksdb(spark):
        products = s.drain(s.shared_products(s.read_stream(spark, s.in_files(spark, crowd.withColumn("event_type", F.lit("x")), [lambda d: d])), ["event_type"], 1))
    people = crowd.count()
    assert products.count() == 1 and products.selectExpr("sum(size(left) + size(right))").first()[0] == 2 * people
    found = s.shared_totals(products)
    assert found.count() == people * (people - 1) // 2 and found.where("shared <> 1 OR a >= b").count() == 0


def test_large_counts_are_exact():
    n, people = np.array([3_000_000_001], "int64"), np.array([1, 2], "int64")
    (found,) = s._sum_of_key([(people[:1], n, people[1:], n), (people[:1], np.array([1]), people[1:], np.array([1]))])
    assert found.to_pylist() == [{"a": 1, "b": 2, "shared": 3_000_000_001**2 + 1}]
