import random

import pytest
from pyspark.sql import functions as F

from pathflow.functions.regions import BOX
from pathflow.operators import baseline
from pathflow.operators.region_tree import branch_quads, build_region_tree, contained_quads, open_quads, region_query, region_tests, touched_leaves
from pathflow.operators.value_tree import ValueTree
from pathflow.plans.lower import run
from pathflow.plans.traversal import HERE
from pathflow.sources.dictionary import dictionary
from pathflow.workloads.queries import QUERIES

from .toys import RECT, region


def ids(df):
    return sorted(r.poi for r in df.select("poi").collect())


def test_toy_rounds_and_answers(spark):
    t = region(spark)
    rounds = {}
    for r in open_quads(t, RECT).collect():
        rounds.setdefault(r["round"], set()).add(r.quad)
    assert rounds == {0: {1}, 1: {2, 3, 4}, 2: {6, 8, 9}}
    assert {r.quad for r in contained_quads(t, RECT).collect()} == {9}
    for method in ("scan", "plain", "branching"):
        assert ids(region_query(t, RECT, method)) == [13, 14, 18]
    assert {r.poi: r.weight for r in region_query(t, RECT, "overlay").collect()} == {13: 1, 14: 2, 18: 1}


def test_toy_counts_of_tests(spark):
    rows = {r.method: (r.region_tests, r.containment_tests, r.results) for r in region_tests(region(spark), RECT).collect()}
    assert rows == {"scan": (9, 0, 3), "plain": (12, 0, 3), "branching": (11, 7, 3), "overlay": (12, 7, 3)}


def test_toy_as_walk_of_the_algebra(spark):
    t = region(spark)
    g = t.as_graph()
    x0, y0, x1, y1 = map(float, RECT)
    body = HERE.out("sub").keep("bl_x", "<=", x1).keep("bl_y", "<=", y1).keep("tr_x", ">=", x0).keep("tr_y", ">=", y0)
    found = run(g, spark, body.power(3), [(20 << 56) + 1]).collect()
    assert sorted(r.pos & ((1 << 56) - 1) for r in found) == [13, 14, 18]


def points(spark, rows):
    return spark.createDataFrame([(i, float(x), float(y), float(u), float(v)) for i, (x, y, u, v) in enumerate(rows)], "poi long, " + ", ".join(f"{c} double" for c in BOX))


@pytest.mark.parametrize("rect", [(0, 0, 100, 100), (25, 20, 90, 45), (50, 50, 50, 50), (0, 0, 0, 0), (100, 100, 100, 100), (-9, -9, -1, -1), (25, 25, 50, 50)])
def test_methods_agree_on_points(spark, rect):
    rng = random.Random(5)
    rows = [(x, y, x, y) for x, y in ((rng.choice([0, 25, 50, 75, 100, rng.uniform(0, 100)]), rng.uniform(0, 60) ** 1.1 % 100) for _ in range(300))] + [(50, 50, 50, 50)] * 9
    t = build_region_tree(points(spark, rows), (0, 0, 100, 100), 4, 8)
    want = [i for i, (x, y, _, _) in enumerate(rows) if rect[0] <= x <= rect[2] and rect[1] <= y <= rect[3]]
    for method in ("scan", "plain", "branching", "prefix", "overlay"):
        assert ids(region_query(t, rect, method)) == want, method
    quads = t.quads.join(branch_quads(t, rect).where("contained").select("quad"), "quad")
    assert quads.where(~((F.col("bl_x") >= rect[0]) & (F.col("tr_x") <= rect[2]))).count() == 0
    depth = {r.poi: r.depth for r in t.pois.collect()}
    top = t.quads.where((F.col("bl_x") >= rect[0]) & (F.col("bl_y") >= rect[1]) & (F.col("tr_x") <= rect[2]) & (F.col("tr_y") <= rect[3])).agg(F.min("depth")).first()[0]
    if top == 0:  # the whole plane: a leaf at depth d has d + 1 contained quads, and is tested once
        assert all(r.weight == depth[r.poi] + 2 for r in region_query(t, rect, "overlay").collect())


@pytest.mark.parametrize("assign", ["enclosing", "every"])
def test_boxes(spark, assign):
    rng = random.Random(6)
    rows = [(x, y, x + rng.uniform(0, 20), y + rng.uniform(0, 20)) for x, y in ((rng.uniform(0, 80), rng.uniform(0, 80)) for _ in range(200))]
    t = build_region_tree(points(spark, rows), (0, 0, 100, 100), 8, 6, assign)
    rect = (30, 30, 55, 60)
    want = [i for i, (a, b, c, d) in enumerate(rows) if a <= 55 and b <= 60 and c >= 30 and d >= 30]
    for method in ("plain", "branching"):
        assert sorted(set(ids(region_query(t, rect, method)))) == want
    if assign == "enclosing":
        assert ids(region_query(t, rect, "prefix")) == want


def test_degenerate_trees(spark):
    for rows in ([], [(5, 5, 5, 5)], [(5, 5, 5, 5)] * 40):
        t = build_region_tree(points(spark, rows), (0, 0, 10, 10), 4, 5)
        for method in ("scan", "plain", "branching", "prefix"):
            assert len(ids(region_query(t, (0, 0, 10, 10), method))) == len(rows)
    with pytest.raises(ValueError):
        build_region_tree(points(spark, []), (0, 0, 10, 10), 0)
    with pytest.raises(ValueError):
        region_query(t, (5, 5, 1, 1))


def test_guessing_numbers(spark):
    g = {r.target: r.guesses for r in baseline.guess_numbers(spark, 1, 100).collect()}
    assert len(g) == 100 and max(g.values()) == 7 and g[50] == 1
    assert {r.target: r.guesses for r in baseline.guess_numbers_linear(spark, 1, 100).collect()} == {i: i for i in range(1, 101)}


def test_guesses_of_a_table_are_those_of_the_whole_range(spark):
    some = spark.createDataFrame([(3,), (8,), (40,)], "k long")
    for guess in (baseline.guess_numbers, baseline.guess_numbers_linear):
        whole = {r.target: r.guesses for r in guess(spark, 3, 40).collect()}
        assert {r.target: r.guesses for r in guess(spark, 3, 40, some).collect()} == {k: whole[k] for k in (3, 8, 40)}


@pytest.mark.parametrize("name", ["guess_number", "guess_number_linear"])
def test_guesses_read_the_parts(spark, name):
    keys = {r[0] for r in spark.read.parquet("/root/testdata/sf0.001/part.parquet").select("p_partkey").collect()}
    found = QUERIES[name](spark, "/root/testdata/sf0.001")
    assert {r.target for r in found.collect()} == keys and any("part.parquet" in f for f in found.inputFiles())


def test_value_tree(spark):
    data = spark.createDataFrame([(i, i * 3) for i in range(100)] + [(100, 6), (101, None)], "key long, value long")
    for fanout in (2, 7, 200):
        t = ValueTree(data, 1, fanout)
        assert sorted(r.pos & 0xFFFF for r in t.lookup(spark, 6).collect()) == [2, 100]
        assert sorted(r.pos & 0xFFFF for r in t.range(spark, 10, 20).collect()) == [4, 5, 6]
        assert t.lookup(spark, 7).count() == 0
    assert ValueTree(data, 1, 2).levels == 7


def test_dictionary_and_bisection(spark):
    words = spark.createDataFrame([(w,) for w in ["b", "a", "c", "a", None, "z"]], "w string")
    d = dictionary(words, "w")
    assert {r.w: r.key for r in d.collect()} == {"a": 0, "b": 1, "c": 2, "z": 3}
    assert [r.value for r in baseline.bisect_lookup(spark, d, "w", "z").collect()] == ["z"]
    assert baseline.bisect_lookup(spark, d, "w", "q").count() == 0


def test_flow_graph_of_the_toy(spark):
    from pathflow.operators.region_walks import flow

    found = run(region(spark).as_graph(), spark, flow(RECT), [(20 << 56) + 1]).collect()
    assert {r.pos & ((1 << 56) - 1): r.weight for r in found} == {13: 1, 14: 2, 18: 1}


def test_boxes_hang_under_every_leaf_they_touch(spark):
    """Against brute force over leaves: boxes on borders of quads, points, boxes as large as the plane, and leaves without a centre; few rows hold them."""
    rng = random.Random(8)
    spot = lambda: (rng.choice([25, 50, 75, 12.5]) if rng.random() < 0.3 else rng.uniform(0, 100))
    rows = [(min(a, c), min(b, d), max(a, c), max(b, d)) for a, b, c, d in ((spot(), spot(), spot(), spot()) for _ in range(150))]
    rows += [(x, y, x, y) for x, y in ((spot() / 4, spot() / 4) for _ in range(150))] + [(0, 0, 100, 100), (25, 25, 50, 50), (100, 100, 100, 100), (0, 99, 100, 100)]
    t = build_region_tree(points(spark, rows), (0, 0, 100, 100), 2, 6, "every")
    leaves = [(r.quad, r.bl_x, r.bl_y, r.tr_x, r.tr_y) for r in t.quads.where("leaf").collect()]
    due = sorted((i, q) for i, (a, b, c, d) in enumerate(rows) for q, x, y, u, v in leaves if a <= u and c >= x and b <= v and d >= y)
    assert sorted((r.poi, r.quad) for r in touched_leaves(t).collect()) == due
    assert t.pois.count() * 3 < len(due)
    assert t.pois.groupBy("poi").count().agg(F.max("count")).first()[0] <= 12 * 6


@pytest.mark.parametrize("method", ["plain", "branching", "prefix"])
def test_every_finds_boxes_where_no_centre_lies(spark, method):
    """A large box reaches into a part of the plane that holds no centre of any."""
    rows = [(x, x, x + 1, x + 1) for x in range(30)] + [(0, 0, 100, 100)]
    t = build_region_tree(points(spark, rows), (0, 0, 100, 100), 2, 6, "every")
    assert set(ids(region_query(t, (90, 0, 95, 5), method))) == {30}
    assert set(ids(region_query(t, (101, 0, 105, 5), method))) == set()
