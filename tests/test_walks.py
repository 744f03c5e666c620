from collections import Counter

import pytest
from pyspark.sql import functions as F

from pathflow.operators import baseline, recommend
from pathflow.plans.lower import materialize_edge, run, touched
from pathflow.plans.rewrite import cost, optimize, reverse_walk
from pathflow.plans.text import parse_walk
from pathflow.plans.traversal import HERE, BindError, compose, kind_after, partial
from pathflow.sources.graph import UnknownKey, UnknownLabel

from .toys import bag, friends, graph, taste


def test_names_of_friends(spark):
    g = friends(spark)
    walk = compose(HERE.values("name"), HERE.head(), HERE.keep_label("friend"), HERE.out_edges())
    assert bag(run(g, spark, walk, [1]), "value") == {"Bo": 1, "Cy": 1, "Di": 1}
    assert bag(run(g, spark, walk, [1], rewrite=False), "value") == {"Bo": 1, "Cy": 1, "Di": 1}


def test_content_walks(spark):
    g = taste(spark)
    assert bag(run(g, spark, recommend.content_neighbors(), [3])) == {2: 1}
    assert bag(run(g, spark, recommend.content_by_likes(), [7])) == {2: 1, 5: 1}


def test_collaborative_walks(spark):
    g = taste(spark)
    assert bag(run(g, spark, recommend.similar_people(), [7])) == {1: 1}
    assert bag(run(g, spark, recommend.collaborative(), [7])) == {2: 1, 3: 1, 5: 1}
    new = recommend.recommend_unknown(g, spark, recommend.collaborative(), [7])
    assert bag(new) == {2: 1, 5: 1}


def test_ten_shared_likes_count_ten_times(spark):
    shared = [(p, r) for p in (1, 2) for r in range(100, 110)]
    g = graph(spark, {"likes": [*shared, (2, 200)]})
    assert bag(run(g, spark, recommend.similar_people(), [1])) == {2: 10}
    assert all(w >= 10 for w in bag(run(g, spark, recommend.collaborative(), [1])).values())


@pytest.mark.parametrize("labels", [("friend",), ("kin",), ("friend", "kin"), ()])
def test_keep_and_drop_are_complements(spark, labels):
    g = friends(spark)
    every = {r.eid: r.label for r in run(g, spark, HERE.out_edges(), [1, 2]).collect()}
    kept = run(g, spark, HERE.out_edges().keep_label(*labels), [1, 2]).count() if labels else 0
    dropped = run(g, spark, HERE.out_edges().drop_label(*labels), [1, 2]).count() if labels else 5
    assert kept + dropped == 5 and len(every) <= 5


def test_missing_property_fails_keep_and_passes_drop(spark):
    g = friends(spark)
    ids = [1, 2, 9]  # 9 has no name
    assert set(bag(run(g, spark, HERE.keep("name", "=", "Ada"), ids))) == {1}
    assert set(bag(run(g, spark, HERE.drop("name", "=", "Ada"), ids))) == {2, 9}


def test_linear_in_the_start_and_associative(spark):
    g = taste(spark)
    a, b, both = (bag(run(g, spark, recommend.liked(), i)) for i in ([7], [1, 1], [7, 1, 1]))
    assert both == {k: a.get(k, 0) + b.get(k, 0) for k in a.keys() | b.keys()}
    x, y, z = HERE.out("likes"), HERE.into("likes"), HERE.out("likes")
    assert ((x >> y) >> z) == (x >> (y >> z))


@pytest.mark.parametrize("mode", ["rows", "paths"])
def test_modes_agree(spark, mode):
    g = taste(spark)
    out = run(g, spark, HERE.out("likes").into("likes").out("likes"), [7], mode=mode).groupBy("pos").sum("weight")
    assert {r[0]: r[1] for r in out.collect()} == bag(run(g, spark, HERE.out("likes").into("likes").out("likes"), [7]))


def test_simple_paths(spark):
    g = taste(spark)
    out = run(g, spark, HERE.out("likes").into("likes").simple_path(), [7], mode="paths").collect()
    assert [[p.id for p in r.path if p.kind == "V"] for r in out] == [[7, 3, 1]]


def test_parallel_edges_and_loops(spark):
    g = graph(spark, {"e": [(1, 2), (1, 2), (1, 1)]})
    assert bag(run(g, spark, HERE.out("e"), [1])) == {2: 2, 1: 1}
    assert bag(run(g, spark, HERE.both("e"), [1])) == {2: 2, 1: 1}
    assert bag(run(g, spark, HERE.out("e").dedup(), [1])) == {2: 1, 1: 1}


def test_empty_starts_and_unknown_names(spark):
    g = friends(spark)
    out = run(g, spark, HERE.out("friend").values("name"), [])
    assert out.count() == 0 and out.columns == ["value", "weight"]
    assert run(g, spark, HERE.out_edges().keep_label("none"), [1]).count() == 0
    with pytest.raises(UnknownLabel):
        run(g, spark, HERE.out("none"), [1])
    with pytest.raises(UnknownKey):
        run(g, spark, HERE.values("none"), [1])


def test_binding(spark):
    assert kind_after(HERE.out_edges("a").head().values("x")) == "S"
    for bad in (HERE.head(), HERE.out_edges("a").out_edges("a"), HERE.drop_marked("never"), HERE.values("x").out("a")):
        with pytest.raises(BindError):
            kind_after(bad)
    with pytest.raises(BindError):
        run(friends(spark), spark, HERE.repeat(HERE.out("friend")), [1])
    assert partial(type(HERE).keep_label, "friend")(HERE.out_edges()) == HERE.out_edges().keep_label("friend")


def test_repeat_and_power(spark):
    g = graph(spark, {"next": [(1, 2), (2, 3), (3, 4)]})
    assert bag(run(g, spark, HERE.out("next").power(3), [1])) == {4: 1}
    assert bag(run(g, spark, HERE.repeat(HERE.out("next"), "all", max_depth=10), [1])) == {2: 1, 3: 1, 4: 1}
    assert bag(run(g, spark, HERE.repeat(HERE.out("next"), "last", max_depth=10), [1])) == {4: 1}


def test_branch_overlay_meet_minus(spark):
    g = friends(spark)
    walk = HERE.branch("name", "=", "Ada", HERE.out("friend"), HERE.out("kin"))
    assert bag(run(g, spark, walk, [1, 2])) == {2: 1, 3: 2, 4: 1}
    assert bag(run(g, spark, HERE.overlay(HERE.out("friend"), HERE.out("kin")), [1, 2])) == {2: 1, 3: 2, 4: 1, 5: 1}
    assert bag(run(g, spark, HERE.out("friend").intersect(HERE.keep_element([3])), [1])) == {3: 1}
    assert bag(run(g, spark, HERE.out("friend").minus(HERE.keep_element([3])), [1])) == {2: 1, 4: 1}


def test_rank_ties_by_id(spark):
    g = graph(spark, {"likes": [(1, 9), (1, 5), (2, 9), (2, 3)]})
    rows = run(g, spark, HERE.out("likes").rank(2), [1, 2]).collect()
    assert [(r.pos, r.weight) for r in rows] == [(9, 2), (3, 1)]
    each = run(g, spark, HERE.out("likes").rank(1), [1, 2], per_origin=True).collect()
    assert sorted((r.origin, r.pos) for r in each) == [(1, 5), (2, 3)]


def test_rewrites(spark):
    g = taste(spark)
    better, fired = optimize(HERE.out_edges().keep_label("likes").head(), g)
    assert fired == ["fuse_labels"] and better == HERE.out("likes")
    walk = HERE.out_edges("likes").tail()
    assert optimize(walk, g)[1] == ["collapse_roundtrip"]
    assert bag(run(g, spark, walk, [7, 1])) == bag(run(g, spark, walk, [7, 1], rewrite=False)) == {7: 2, 1: 3}
    assert reverse_walk(HERE.out("likes").into("feature")) == HERE.out("feature").into("likes")
    assert cost(recommend.collaborative())["hops"] == 3


def test_virtual_edge_equals_the_walk(spark):
    g = graph(spark, {"friend": [(1, 2), (2, 3), (1, 4), (4, 3), (3, 1)]})
    start = spark.createDataFrame([(i,) for i in (1, 2, 3, 4)], "pos long")
    stored = materialize_edge(g, spark, recommend.friend_of_friend(), "foaf", start)
    walk = recommend.friend_of_friend().out("friend")
    assert optimize(walk, stored)[1] == ["use_virtual_edge:foaf"]
    assert bag(run(stored, spark, walk, [1, 3])) == bag(run(g, spark, walk, [1, 3]))


def test_text_form(spark):
    assert parse_walk("mark me /likes> /<likes !me /likes> rank 10") == (HERE.mark("me").out("likes").into("likes").drop_marked("me").out("likes").rank(10))
    assert parse_walk("/likes>e +likes .head [name = Ada] .name") == HERE.out_edges("likes").keep_label("likes").head().keep("name", "=", "Ada").values("name")
    assert parse_walk("(/next>)*3 (/a> | /<b)") == HERE.out("next").power(3) >> HERE.overlay(HERE.out("a"), HERE.into("b"))
    for bad in ("/likes> )", "(/a>", "[name]", "?"):
        with pytest.raises(BindError):
            parse_walk(bad)


def test_matrix_products_equal_the_walk(spark):
    g = taste(spark)
    out = baseline.matrix_walk(g, spark, [("likes", "out"), ("likes", "in"), ("likes", "out")], [7], clear_start_after=2)
    assert bag(out) == bag(run(g, spark, recommend.collaborative(), [7]))


def test_touched_is_blind_to_padding(spark):
    g = taste(spark)
    pad = graph(spark, {"likes": [(7, 3), (7, 4), (1, 3), (1, 2), (1, 5), (107, 103), (101, 103)], "feature": []})
    rows = [[(r.positions, r.weight) for r in touched(x, spark, recommend.collaborative(), [7]).orderBy("step").collect()] for x in (g, pad)]
    assert rows[0] == rows[1]


def test_touched_joins_once_an_edge_step(spark):
    g, walk, joins = taste(spark), HERE, []
    for _ in range(2):
        walk = walk.out("likes").into("likes")
        joins.append(touched(g, spark, walk, [7])._jdf.queryExecution().optimizedPlan().toString().count("Join"))
    assert joins == [2, 4]


def test_scores_and_quotient(spark):
    g = taste(spark)
    assert [(r.pos, r.shared, round(r.score, 6)) for r in recommend.content_scores(g, spark, [3], normalize="cosine").collect()] == [(2, 1, 1.0)]
    e = g.edges("feature")
    a = {(r.a, r.b): r.weight for r in recommend.shared_pairs(e).collect()}
    assert a == {(r.a, r.b): r.weight for r in recommend.signature_quotient(e).collect()}
    with pytest.raises(ValueError):
        recommend.content_scores(g, spark, [3], normalize="odd")


def test_sampling_is_repeatable(spark):
    g = graph(spark, {"likes": [(1, i) for i in range(100)]})
    a = bag(run(g, spark, HERE.out("likes").sample(0.5, 3), [1]))
    assert a == bag(run(g, spark, HERE.out("likes").sample(0.5, 3), [1])) and 25 < len(a) < 75
    assert sum(bag(run(g, spark, HERE.sample_out("likes", 4, 1), [1])).values()) == 4


def test_validate_and_subgraph(spark):
    g = friends(spark)
    found = {(r.label, r.check): r.n for r in g.validate().collect()}
    assert set(found.values()) == {0}
    bad = graph(spark, {"friend": [(1, 9)]}, {1: "Ada"})
    assert {(r.check, r.n) for r in bad.validate().collect() if r.n} == {("dangling_dst", 1)}
    assert g.subgraph("friend", lambda e: e.dst > 2).edges("friend").count() == 2
    assert {(r.src, r.dst) for r in g.reverse().edges("kin").collect()} == {(5, 1), (3, 2)}


def test_layout_is_two_clustered_copies(spark, tmp_path):
    g = friends(spark)
    g.write_layout(f"file://{tmp_path}/layout", 2)
    for side in ("src", "dst"):
        back = spark.read.parquet(f"file://{tmp_path}/layout/by_{side}")
        assert {(r.label, r.src, r.dst) for r in back.collect()} == {("friend", 1, 2), ("friend", 1, 3), ("friend", 1, 4), ("kin", 1, 5), ("kin", 2, 3)}
    plan = back.where("label = 'kin' AND src = 1")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(label" in plan and "EqualTo(src,1)" in plan


def test_explain_names_rules(spark):
    from pathflow.plans.explain import explain

    text = explain(taste(spark), spark, HERE.out_edges().keep_label("likes").head(), [7])
    assert "fuse_labels" in text and "ends in V" in text and "Join" in text


FRIENDS = {"friend": [(1, 2), (2, 1), (2, 6), (3, 6), (6, 1), (6, 3), (1, 6)], "likes": [(1, 100), (1, 101), (2, 100), (3, 101), (6, 101), (6, 102)]}


def weights(df, *more):
    return sorted((*(r[c] for c in more), r["pos"], r["weight"]) for r in df.collect())


def test_arms_end_their_own_marks(spark):
    from pathflow.operators.recommend import liked, similar_people

    g = graph(spark, FRIENDS)
    both = run(g, spark, HERE.overlay(similar_people(), HERE.out("friend")), [1])
    apart = Counter()
    for w in (similar_people(), HERE.out("friend")):
        for r in run(g, spark, w, [1]).collect():
            apart[r.pos] += r.weight
    assert weights(both) == sorted(apart.items())
    per = run(g, spark, HERE.overlay(similar_people(), HERE.out("friend")) >> liked(), [1, 3], per_origin=True)
    one = [(o, p, w) for o in (1, 3) for p, w in weights(run(g, spark, HERE.overlay(similar_people(), HERE.out("friend")) >> liked(), [o]))]
    assert weights(per, "origin") == sorted(one)


def test_marks_set_before_arms_are_seen_in_and_after_them(spark):
    g = graph(spark, FRIENDS)
    inside = run(g, spark, HERE.mark("me").overlay(HERE.out("friend").out("friend").drop_marked("me"), HERE.out("friend")), [1, 2])
    want = Counter()
    out = {}
    for a, b in FRIENDS["friend"]:
        out.setdefault(a, []).append(b)
    for s in (1, 2):
        want.update(c for b in out[s] for c in out.get(b, []) if c != s)
        want.update(out[s])
    assert weights(inside) == sorted(want.items())
    later = run(g, spark, HERE.mark("me").overlay(HERE.out("friend"), HERE.out("friend").out("friend")).drop_marked("me"), [1, 2])
    want = Counter()
    for s in (1, 2):
        want.update(x for x in out[s] if x != s)
        want.update(c for b in out[s] for c in out.get(b, []) if c != s)
    assert weights(later) == sorted(want.items())


def test_intersect_with_an_arm_that_ends_in_drop_marked(spark):
    g = graph(spark, FRIENDS)
    arm = HERE.out("friend").mark("p").into("friend").drop_marked("p")
    got = weights(run(g, spark, HERE.overlay(*[HERE] * 6).intersect(arm), [1, 3], per_origin=True), "origin")
    reach = {(r.origin, r.pos): r.weight for r in run(g, spark, arm, [1, 3], per_origin=True).collect()}
    assert got == sorted((o, o, min(6, 6 * reach[o, o])) for o in (1, 3) if (o, o) in reach) == [(1, 1, 6), (3, 3, 6)]
    assert len({(r[0], r[1]) for r in got}) == len(got)


@pytest.mark.parametrize("mode", ["bulk", "rows"])
def test_set_steps_count_alike_in_rows_and_bulk(spark, mode):
    g = graph(spark, FRIENDS)
    two, one = HERE.out("friend").out("friend"), HERE.overlay(HERE.out("friend"), HERE.out("friend"))
    out = {}
    for a, b in FRIENDS["friend"]:
        out.setdefault(a, []).append(b)
    start = spark.createDataFrame([(1,), (2,)], "pos long")

    def counted(walk):
        got = Counter()
        for r in run(g, spark, walk, frame=start, mode=mode).collect():
            got[r.pos] += r.weight
        return got

    base = HERE.overlay(HERE, HERE, HERE)
    assert counted(base.intersect(two)) == Counter({k: min(3 * (k in (1, 2)), v) for k, v in Counter(c for s in (1, 2) for _ in range(3) for b in out[s] for c in out.get(b, [])).items() if k in (1, 2)})
    assert counted(base.minus(one)) == Counter({1: 3, 2: 3}) - Counter(b for s in (1, 2) for _ in range(3) for b in out[s] * 2)
    assert counted(base.intersect(two, distinct=True)) == Counter(k for k in (1, 2) if any(k in out.get(b, []) for s in (1, 2) for b in out[s]))
    with pytest.raises(BindError):
        run(g, spark, base.intersect(two), frame=start, mode="paths")


def test_edge_ids_and_samples_ignore_parallelism(spark):
    from pathflow.sources.dictionary import global_rank

    rows = [(i % 17, (i * 7) % 23) for i in range(200)]
    few, many = (global_rank(spark.createDataFrame(rows, "src long, dst long").repartition(n), [F.asc("src"), F.asc("dst")], "eid") for n in (2, 7))
    assert sorted(map(tuple, few.collect())) == sorted(map(tuple, many.collect()))


def test_adjacent_filters_meet_properties_once(spark):
    walk = HERE.out("friend").keep("c_name", "=", "x").drop("c_acctbal", "<", 0).keep("c_nationkey", "=", 3).dedup().dedup()
    better, fired = optimize(HERE.overlay(walk, HERE), graph(spark, FRIENDS))
    assert [s.op for s in better.steps[0].args[0][0].steps] == ["edges", "end", "properties", "dedup"] and "fuse_properties" in fired
