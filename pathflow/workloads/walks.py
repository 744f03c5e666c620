"""Steps, walks and recommendation on the given tables."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import baseline, measures, recommend, reduce
from ..plans.explain import exchanges
from ..plans.lower import materialize_edge, run, touched
from ..plans.rewrite import cost, optimize
from ..plans.text import parse_walk
from ..plans.traversal import HERE, compose
from ..sources.graph import KEY_BITS, EdgeLabel, PropertyGraph, key_of
from ..sources.scratch import shared_dir, stored
from .graphs import CUSTOMER, DOCUMENT, NATION, PART, SUPPLIER, Graphs
from .registry import query

ME, NAME = 7, "Customer#000000007"


def ids(code: int, *keys: int) -> list[int]:
    return [(code << 56) + k for k in keys]


def keyed(df: DataFrame, name: str, weight: str | None = "times", *more: str) -> DataFrame:
    out = [key_of(F.col("pos")).alias(name)]
    if weight:
        out.append(F.col("weight").alias(weight))
    return df.select(*out, *more)


def key(column: str) -> Column:
    return key_of(F.col(column))


LIKES = "likes AS (SELECT o_custkey AS src, l_partkey AS dst, count(*) AS n_buys FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2)"
MULTI = "multi AS (SELECT o_custkey AS src, l_partkey AS dst, l_returnflag AS flag FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"
FEATURE = """feature AS (SELECT p_partkey AS src, 'brand:' || p_brand AS dst FROM part UNION ALL SELECT p_partkey, 'type:' || p_type FROM part
  UNION ALL SELECT p_partkey, 'size:' || p_size FROM part UNION ALL SELECT p_partkey, 'word:' || unnest(string_split(p_name, ' ')) FROM part)"""
FRIEND = f"""{LIKES}, friend AS (SELECT DISTINCT a.src, b.src AS dst FROM likes a JOIN likes b ON a.dst = b.dst AND a.src <> b.src
  JOIN customer ca ON ca.c_custkey = a.src JOIN customer cb ON cb.c_custkey = b.src AND ca.c_nationkey = cb.c_nationkey)"""


def total(x: str) -> str:
    return f"CAST(sum({x}) AS BIGINT)"


# -- friends of a person

FRIEND_NAMES = f"WITH {FRIEND} SELECT b.c_name AS friend_name, count(*) AS times FROM customer a JOIN friend f ON f.src = a.c_custkey JOIN customer b ON b.c_custkey = f.dst WHERE a.c_name = '{NAME}' GROUP BY 1"


@query(FRIEND_NAMES)
def friend_names_relational(g: Graphs) -> DataFrame:
    friend = g.commerce().edges("friend").select(key("src").alias("src"), key("dst").alias("dst"))
    return baseline.relational_friend_names(g.spark, g.table("customer"), friend, NAME)


def named(g: Graphs) -> DataFrame:
    """The start by a property: an index lookup, then local steps."""
    return g.commerce().with_property("c_name").where(F.col("value") == NAME).select(F.col("vid").alias("pos"))


@query(FRIEND_NAMES)
def friend_names_walk(g: Graphs) -> DataFrame:
    walk = compose(HERE.values("c_name"), HERE.head(), HERE.keep_label("friend"), HERE.out_edges())
    return run(g.commerce(), g.spark, walk, frame=named(g)).select(F.col("value").alias("friend_name"), F.col("weight").alias("times"))


@query(f"WITH {FRIEND} SELECT src AS person, count(*) AS friends, count(DISTINCT c_name) AS names FROM friend JOIN customer ON c_custkey = dst GROUP BY 1")
def friend_names_all(g: Graphs) -> DataFrame:
    start = g.commerce().vertices("customer").select(F.col("vid").alias("pos"))
    names = run(g.commerce(), g.spark, HERE.out("friend").values("c_name"), frame=start, per_origin=True)
    return names.groupBy(key("origin").alias("person")).agg(F.sum("weight").alias("friends"), F.count_distinct("value").alias("names"))


@query(f"WITH {FRIEND} SELECT src, dst FROM friend WHERE src IN (7, 8)")
def friend_edges_out(g: Graphs) -> DataFrame:
    return run(g.commerce(), g.spark, HERE.out_edges("friend"), ids(CUSTOMER, 7, 8)).select(key("src").alias("src"), key("dst").alias("dst"))


@query(f"WITH {FRIEND} SELECT src, dst FROM friend WHERE dst IN (7, 8)")
def friend_edges_in(g: Graphs) -> DataFrame:
    return run(g.commerce(), g.spark, HERE.in_edges("friend"), ids(CUSTOMER, 7, 8)).select(key("src").alias("src"), key("dst").alias("dst"))


@query(f"WITH {FRIEND} SELECT src AS vertex, count(*) AS times FROM friend WHERE dst IN (7, 8) GROUP BY 1")
def edge_tails(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, HERE.in_edges("friend").tail(), ids(CUSTOMER, 7, 8)), "vertex")


@query(f"WITH {FRIEND} SELECT dst AS vertex, count(*) AS times FROM friend WHERE src IN (7, 8) GROUP BY 1")
def edge_heads(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, HERE.out_edges("friend").head(), ids(CUSTOMER, 7, 8)), "vertex")


@query(f"WITH {FRIEND} SELECT c_mktsegment AS value, count(*) AS times FROM friend JOIN customer ON c_custkey = dst WHERE src = 7 GROUP BY 1")
def vertex_values(g: Graphs) -> DataFrame:
    return run(g.commerce(), g.spark, HERE.out("friend").values("c_mktsegment"), ids(CUSTOMER, ME)).select("value", F.col("weight").alias("times"))


@query("SELECT l_quantity AS value, count(*) AS times FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE o_custkey = 7 GROUP BY 1")
def edge_values(g: Graphs) -> DataFrame:
    walk = HERE.out("placed").out_edges("contains").values("l_quantity")
    return run(g.commerce(), g.spark, walk, ids(CUSTOMER, ME)).select("value", F.col("weight").alias("times"))


AROUND = f"""WITH {FRIEND}, around AS (SELECT 'likes' AS label, dst FROM likes WHERE src = 7 UNION ALL SELECT 'friend', dst FROM friend WHERE src = 7
  UNION ALL SELECT 'placed', o_orderkey FROM orders WHERE o_custkey = 7 UNION ALL SELECT 'in_nation', c_nationkey FROM customer WHERE c_custkey = 7)
  SELECT label, count(*) AS edges FROM around WHERE label {{}} IN ('likes', 'friend') GROUP BY 1"""
MIXED = ("placed", "likes", "friend", "in_nation")


@query(AROUND.format(""))
def label_keep(g: Graphs) -> DataFrame:
    e = run(g.commerce(), g.spark, HERE.out_edges(*MIXED).keep_label("likes", "friend"), ids(CUSTOMER, ME))
    return e.groupBy("label").agg(F.count("*").alias("edges"))


@query(AROUND.format("NOT"))
def label_drop(g: Graphs) -> DataFrame:
    e = run(g.commerce(), g.spark, HERE.out_edges(*MIXED).drop_label("likes", "friend"), ids(CUSTOMER, ME))
    return e.groupBy("label").agg(F.count("*").alias("edges"))


def _all_documents(g: Graphs, walk) -> DataFrame:
    start = g.table("documents").select((F.col("doc_id") + (DOCUMENT << 56)).alias("pos"))
    return keyed(run(g.documents(), g.spark, walk, frame=start), "doc", None)


@query("SELECT d.doc_id AS doc FROM documents d JOIN labels l ON l.doc_id = d.doc_id WHERE quality = 1")
def prop_keep(g: Graphs) -> DataFrame:
    return _all_documents(g, HERE.keep("quality", "=", 1))


@query("SELECT d.doc_id AS doc FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id WHERE quality IS NULL OR quality <> 1")
def prop_drop(g: Graphs) -> DataFrame:
    return _all_documents(g, HERE.drop("quality", "=", 1))


SOME = tuple(range(0, 1000))
LIKED_BY = f"WITH {LIKES} SELECT dst AS part, count(*) AS times FROM likes WHERE src IN (7, 9) AND dst {{}} 1000 GROUP BY 1"


@query(LIKED_BY.format("<"))
def element_keep(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, HERE.out("likes").keep_element(ids(PART, *SOME)), ids(CUSTOMER, 7, 9)), "part")


@query(LIKED_BY.format(">="))
def element_drop(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, HERE.out("likes").drop_element(ids(PART, *SOME)), ids(CUSTOMER, 7, 9)), "part")


@query(f"WITH {LIKES}, s AS (SELECT unnest([7, 7, 9]) AS p) SELECT dst AS part, count(*) AS weight FROM s JOIN likes ON src = p GROUP BY 1")
def multi_start_walk(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, HERE.out("likes"), ids(CUSTOMER, 7, 7, 9)), "part", "weight")


@query("SELECT r_name AS value, count(*) AS times FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY 1")
def locate_region_path(g: Graphs) -> DataFrame:
    start = g.commerce().vertices("customer").select(F.col("vid").alias("pos"))
    return run(g.commerce(), g.spark, HERE.out("in_nation").out("in_region").values("r_name"), frame=start).select("value", F.col("weight").alias("times"))


@query(f"WITH {FRIEND} SELECT dst AS customer, count(*) AS times FROM friend WHERE src = 7 GROUP BY 1")
def undirected_neighbors(g: Graphs) -> DataFrame:
    return keyed(run(g.cofriends(), g.spark, HERE.both("cofriend"), ids(CUSTOMER, ME)), "customer")


FOAF = f"WITH {FRIEND}, two AS (SELECT b.dst AS person FROM friend a JOIN friend b ON b.src = a.dst WHERE a.src = 7)"


@query(f"{FOAF} SELECT person, count(*) AS times FROM two GROUP BY 1")
def foaf(g: Graphs) -> DataFrame:
    return keyed(recommend.foaf(g.commerce(), g.spark, ids(CUSTOMER, ME)), "person")


@query(f"{FOAF} SELECT person, count(*) AS times FROM two WHERE person <> 7 AND person NOT IN (SELECT dst FROM friend WHERE src = 7) GROUP BY 1")
def foaf_new_only(g: Graphs) -> DataFrame:
    return keyed(recommend.foaf(g.commerce(), g.spark, ids(CUSTOMER, ME), exclude_self=True, exclude_direct=True), "person")


@query(f"{FOAF} SELECT person, count(*) AS times FROM two GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 20")
def foaf_weighted(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.friend_of_friend().rank(20), ids(CUSTOMER, ME)), "person")


def nation_of_me(g: Graphs) -> DataFrame:
    c = g.table("customer")
    mine = c.where(F.col("c_custkey") == ME).select(F.col("c_nationkey").alias("n"))
    return c.join(F.broadcast(mine), F.col("c_nationkey") == F.col("n")).select((F.col("c_custkey") + (CUSTOMER << 56)).alias("pos"))


def all_customers(g: Graphs) -> DataFrame:
    return g.commerce().vertices("customer").select(F.col("vid").alias("pos"))


@query(f"WITH {LIKES} SELECT a.src AS a, b.src AS b, count(*) AS shared FROM likes a JOIN likes b ON a.dst = b.dst AND a.src <> b.src GROUP BY 1, 2")
def virtual_copurchase(g: Graphs) -> DataFrame:
    """Customer pairs of all nations, both ways."""
    pairs = run(g.commerce(), g.spark, recommend.similar_people(), frame=all_customers(g), per_origin=True)
    return pairs.select(key("origin").alias("a"), key("pos").alias("b"), F.col("weight").alias("shared"))


@query(f"WITH {FRIEND} SELECT c.dst AS person, count(*) AS times FROM friend a JOIN friend b ON b.src = a.dst JOIN friend c ON c.src = b.dst WHERE a.src = 7 GROUP BY 1")
def virtual_edge_reuse(g: Graphs) -> DataFrame:
    """Three friend steps, of which the first two are a stored virtual edge."""
    stored = materialize_edge(g.commerce(), g.spark, recommend.friend_of_friend(), "foaf", nation_of_me(g))
    return keyed(run(stored, g.spark, recommend.friend_of_friend().out("friend"), ids(CUSTOMER, ME)), "person")


# -- recommendation

CONTENT = f"WITH {FEATURE} SELECT b.src AS part, count(*) AS shared FROM feature a JOIN feature b ON b.dst = a.dst AND b.src <> a.src WHERE a.src"


@query(f"{CONTENT} = 3 GROUP BY 1")
def content_similar_part(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.content_neighbors(), ids(PART, 3)), "part", "shared")


@query(f"{CONTENT} IN (3, 5, 8) GROUP BY 1")
def content_similar_set(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.content_neighbors(), ids(PART, 3, 5, 8)), "part", "shared")


@query(f"{CONTENT} IN (3, 5, 8) AND b.src NOT IN (3, 5, 8) GROUP BY 1")
def content_similar_set_all(g: Graphs) -> DataFrame:
    some = ids(PART, 3, 5, 8)
    return keyed(run(g.commerce(), g.spark, recommend.content_neighbors(exclude_all=some), some), "part", "shared")


@query(f"WITH {LIKES} SELECT dst AS part, count(*) AS times FROM likes WHERE src = 7 GROUP BY 1")
def liked_parts(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.liked(), ids(CUSTOMER, ME)), "part")


BY_LIKES = f"WITH {LIKES}, {FEATURE}, content AS (SELECT b.src AS part, count(*) AS weight FROM likes l JOIN feature a ON a.src = l.dst JOIN feature b ON b.dst = a.dst AND b.src <> a.src WHERE l.src = 7 GROUP BY 1)"


@query(f"{BY_LIKES} SELECT part, weight FROM content")
def content_by_likes(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.content_by_likes(), ids(CUSTOMER, ME)), "part", "weight")


PEOPLE = f"{LIKES}, people AS (SELECT b.src AS customer, count(*) AS shared FROM likes a JOIN likes b ON b.dst = a.dst AND b.src <> a.src WHERE a.src = 7 GROUP BY 1)"
CF = f"WITH {PEOPLE}, cf AS (SELECT dst AS part, {total('shared')} AS weight FROM people JOIN likes ON src = customer GROUP BY 1)"


@query(f"WITH {PEOPLE} SELECT customer, shared FROM people")
def similar_customers(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.similar_people(), ids(CUSTOMER, ME)), "customer", "shared")


@query(f"{CF} SELECT part, weight FROM cf")
def cf_recommend(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.collaborative(), ids(CUSTOMER, ME)), "part", "weight")


@query(f"{CF} SELECT part, weight FROM cf WHERE part NOT IN (SELECT dst FROM likes WHERE src = 7)")
def cf_recommend_new(g: Graphs) -> DataFrame:
    return keyed(recommend.recommend_unknown(g.commerce(), g.spark, recommend.collaborative(), ids(CUSTOMER, ME)), "part", "weight")


@query(f"WITH {PEOPLE} SELECT dst AS part, {total('shared')} AS weight FROM people JOIN likes ON src = customer WHERE shared >= 2 GROUP BY 1")
def cf_min_overlap(g: Graphs) -> DataFrame:
    return keyed(recommend.by_overlap(g.commerce(), g.spark, ids(CUSTOMER, ME), min_shared=2), "part", "weight")


@query(f"WITH {PEOPLE} SELECT dst AS part, {total('shared')} AS weight FROM people JOIN likes ON src = customer WHERE shared >= (SELECT count(*) FROM likes WHERE src = 7) * 0.05 GROUP BY 1")
def cf_min_ratio(g: Graphs) -> DataFrame:
    return keyed(recommend.by_overlap(g.commerce(), g.spark, ids(CUSTOMER, ME), min_ratio=0.05), "part", "weight")


@query(
    f"""WITH {MULTI}, people AS (SELECT b.src AS customer, count(*) AS shared FROM multi a JOIN multi b ON b.dst = a.dst AND b.src <> a.src WHERE a.src = 7 GROUP BY 1)
SELECT dst AS part, {total("shared")} AS weight FROM people JOIN multi ON src = customer GROUP BY 1"""
)
def cf_multi_edges(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.collaborative("likes_multi"), ids(CUSTOMER, ME)), "part", "weight")


@query(
    f"""WITH {LIKES}, p AS (SELECT a.src AS customer, b.src AS other, count(*) AS shared FROM likes a JOIN likes b ON b.dst = a.dst AND b.src <> a.src GROUP BY 1, 2)
SELECT customer, count(*) AS people, {total("shared")} AS shares, max(shared) AS max_share FROM p GROUP BY 1"""
)
def cf_all_pairs(g: Graphs) -> DataFrame:
    pairs = recommend.shared_pairs(g.commerce().edges("likes"))
    return pairs.groupBy(key("a").alias("customer")).agg(F.count("*").alias("people"), F.sum("weight").alias("shares"), F.max("weight").alias("max_share"))


@query(
    f"""WITH {LIKES}, p AS (SELECT a.src AS customer, b.src AS other, count(*) AS shared FROM likes a JOIN likes b ON b.dst = a.dst AND b.src <> a.src GROUP BY 1, 2),
r AS (SELECT customer, dst AS part, {total("shared")} AS weight FROM p JOIN likes ON src = other GROUP BY 1, 2)
SELECT customer, part, weight, CAST(row_number() OVER (PARTITION BY customer ORDER BY weight DESC, part) AS INTEGER) AS rank FROM r QUALIFY rank <= 10"""
)
def cf_top10_each(g: Graphs) -> DataFrame:
    """The top 10 of every customer, range by range of origins."""
    out = recommend.best_of_each(g.commerce().edges("likes"), 10)
    return out.select(key("origin").alias("customer"), key("pos").alias("part"), "weight", "rank")


DEGREES = f"WITH {FEATURE}, f AS (SELECT dst, count(*) AS d FROM feature GROUP BY 1), r AS (SELECT src, count(*) AS d FROM feature GROUP BY 1)"
SCORED = "FROM feature a JOIN f ON f.dst = a.dst JOIN feature b ON b.dst = a.dst AND b.src <> a.src JOIN r ON r.src = b.src WHERE a.src = 3"
_OPTIONS = {
    "none": "CAST(count(*) AS DOUBLE)", "feature": "sum(1.0::DOUBLE / f.d)", "resource": "count(*) / max(r.d)", "both": "sum(1.0::DOUBLE / f.d) / max(r.d)",
    "cosine": "count(*) / sqrt(5.0::DOUBLE * max(r.d))", "jaccard": "count(*) / (5 + max(r.d) - count(*))",
}


@query(DEGREES + " " + " UNION ALL ".join(f"SELECT '{o}' AS option, b.src AS part, round({x}, 6) AS score {SCORED} GROUP BY b.src" for o, x in _OPTIONS.items()))
def content_normalized(g: Graphs) -> DataFrame:
    out = None
    for option in _OPTIONS:
        one = recommend.content_scores(g.commerce(), g.spark, ids(PART, 3), normalize=option).select(F.lit(option).alias("option"), key("pos").alias("part"), F.round("score", 6).alias("score"))
        out = one if out is None else out.unionByName(one)
    return out


@query(f"{DEGREES} SELECT b.src AS part, count(*) AS shared, round(sum(ln(((SELECT count(*) FROM r) + 1)::DOUBLE / (f.d + 1))), 6) AS score {SCORED} GROUP BY 1")
def content_idf(g: Graphs) -> DataFrame:
    return recommend.content_scores(g.commerce(), g.spark, ids(PART, 3), novelty="idf").select(key("pos").alias("part"), "shared", F.round("score", 6).alias("score"))


@query(f"{DEGREES} SELECT b.src AS part, count(*) AS shared {SCORED} AND f.d <= 100 GROUP BY 1")
def content_rare_only(g: Graphs) -> DataFrame:
    return recommend.content_scores(g.commerce(), g.spark, ids(PART, 3), novelty="max_degree", max_degree=100).select(key("pos").alias("part"), "shared")


BOTH = f"{CF}, {FEATURE}, content AS (SELECT b.src AS part, count(*) AS weight FROM likes l JOIN feature a ON a.src = l.dst JOIN feature b ON b.dst = a.dst AND b.src <> a.src WHERE l.src = 7 GROUP BY 1)"


def _both(g: Graphs) -> list[tuple[DataFrame, float]]:
    me = ids(CUSTOMER, ME)
    return [(run(g.commerce(), g.spark, recommend.collaborative(), me), 0.7), (run(g.commerce(), g.spark, recommend.content_by_likes(), me), 0.3)]


def _scored(df: DataFrame) -> DataFrame:
    return df.select(key("pos").alias("part"), F.round("score", 6).alias("score"))


@query(
    f"""{BOTH}, u AS (SELECT part, 0.7::DOUBLE * weight / (SELECT max(weight) FROM cf) AS s FROM cf UNION ALL SELECT part, 0.3::DOUBLE * weight / (SELECT max(weight) FROM content) FROM content)
SELECT part, round(sum(s), 6) AS score FROM u GROUP BY 1"""
)
def hybrid_sum(g: Graphs) -> DataFrame:
    return _scored(recommend.hybrid(_both(g), "sum"))


@query(
    f"""{BOTH}, u AS (SELECT part, 0.7::DOUBLE / (60 + row_number() OVER (ORDER BY weight DESC, part)) AS s FROM cf UNION ALL SELECT part, 0.3::DOUBLE / (60 + row_number() OVER (ORDER BY weight DESC, part)) FROM content)
SELECT part, round(sum(s), 6) AS score FROM u GROUP BY 1"""
)
def hybrid_rank(g: Graphs) -> DataFrame:
    return _scored(recommend.hybrid(_both(g), "rank"))


@query(f"{BOTH} SELECT part, CAST(weight AS DOUBLE) AS score FROM cf WHERE part IN (SELECT part FROM content)")
def hybrid_gate(g: Graphs) -> DataFrame:
    return _scored(recommend.hybrid(_both(g), "gate"))


@query(f"{CF} SELECT part FROM cf")
def cf_set_result(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.collaborative().dedup(), ids(CUSTOMER, ME)), "part", None)


WORDS = "words AS (SELECT DISTINCT doc_id AS src, unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS dst FROM documents)"


@query(f"WITH {WORDS} SELECT b.src AS doc, count(*) AS shared FROM words a JOIN words b ON b.dst = a.dst AND b.src <> a.src WHERE a.src = 1 GROUP BY 1")
def cooc_documents(g: Graphs) -> DataFrame:
    """Content walk over all words of the document, however many others have them."""
    return keyed(run(g.documents(), g.spark, recommend.content_neighbors("has_word"), ids(DOCUMENT, 1)), "doc", "shared")


LINKS = """links AS (SELECT DISTINCT page_id AS src, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS dst FROM pages)"""


@query(f"WITH {LINKS} SELECT a.src AS page, b.src AS other, count(*) AS shared FROM links a JOIN links b ON b.dst = a.dst AND b.src <> a.src GROUP BY 1, 2")
def cocited_pages(g: Graphs) -> DataFrame:
    pairs = recommend.shared_pairs(g.pages().edges("links_to"))
    return pairs.select(key("a").alias("page"), key("b").alias("other"), F.col("weight").alias("shared"))


@query("WITH h AS (SELECT page_id AS src, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS dst FROM pages) SELECT a.src AS page, count(*) AS shared FROM h a JOIN h b ON b.dst = a.dst AND b.src <> a.src GROUP BY 1")
def cohost_pages(g: Graphs) -> DataFrame:
    """How many others share a page's host. Out to the host and back over its pages is a degree lookup (rewritten), so no pair is made; the page itself is taken off."""
    start = g.pages().vertices("page").select(F.col("vid").alias("pos"))
    out = run(g.pages(), g.spark, HERE.out("on_host").in_edges("on_host").head(), frame=start, per_origin=True)
    totals = out.groupBy(key("origin").alias("page")).agg((F.sum("weight") - F.count("*")).alias("shared"))
    return totals.where("shared > 0")


@query("WITH s AS (SELECT DISTINCT l_suppkey AS src, l_partkey AS dst FROM lineitem) SELECT b.src AS supplier, count(*) AS shared FROM s a JOIN s b ON b.dst = a.dst AND b.src <> a.src WHERE a.src = 7 GROUP BY 1")
def supplier_alternatives(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, recommend.similar_people("supplies"), ids(SUPPLIER, 7)), "supplier", "shared")


@query("SELECT b.user_id AS user, count(*) AS weight FROM events a JOIN events b ON b.event_type = a.event_type AND b.user_id <> a.user_id WHERE a.user_id = 7 GROUP BY 1")
def user_taste_by_events(g: Graphs) -> DataFrame:
    """Parallel edges: repeats are products of counts; merging after the first hop keeps the work at users * kinds."""
    return keyed(run(g.events(), g.spark, recommend.similar_people("did"), ids(CUSTOMER, ME)), "user", "weight")


@query(f"WITH {PEOPLE} SELECT customer, round(shared / (SELECT count(*) FROM likes WHERE src = 7), 6) AS ratio FROM people")
def shared_ratio(g: Graphs) -> DataFrame:
    me = ids(CUSTOMER, ME)
    people = run(g.commerce(), g.spark, recommend.similar_people(), me)
    own = run(g.commerce(), g.spark, recommend.liked(), me).agg(F.count("*").alias("own"))
    return people.crossJoin(F.broadcast(own)).select(key("pos").alias("customer"), F.round(F.col("weight") / F.col("own"), 6).alias("ratio"))


# -- lists, maps, trees

@query(
    """WITH RECURSIVE c AS (SELECT conv_id AS conv, turn, 0 AS hops FROM conversations WHERE turn = 0
UNION ALL SELECT c.conv, t.turn, hops + 1 FROM c JOIN conversations t ON t.conv_id = c.conv AND t.turn = c.turn + 1)
SELECT conv, CAST(max(hops) AS BIGINT) AS hops, max(turn) AS last_turn FROM c GROUP BY 1"""
)
def conversation_chain(g: Graphs) -> DataFrame:
    """A list walked to exhaustion: next edges come from one window over (conversation, turn)."""
    g.spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")
    g.spark.conf.set("spark.sql.cteRecursionLevelLimit", "10000")
    after = "SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM {turns}"
    return g.spark.sql(
        f"WITH RECURSIVE n AS ({after}), c(conv, turn, hops) AS (SELECT conv_id, min(turn), 0L FROM {{turns}} GROUP BY conv_id UNION ALL SELECT c.conv, n.nxt, hops + 1 FROM c JOIN n ON n.conv_id = c.conv AND n.turn = c.turn WHERE n.nxt IS NOT NULL) "
        "SELECT conv, max(hops) AS hops, max(turn) AS last_turn FROM c GROUP BY conv",
        turns=g.table("conversations"),
    )


@query("SELECT event_id AS event, third FROM (SELECT event_id, lead(event_id, 3) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS third FROM events) WHERE third IS NOT NULL")
def event_chain(g: Graphs) -> DataFrame:
    start = g.events().vertices("event").select(F.col("vid").alias("pos"))
    out = run(g.events(), g.spark, HERE.out("next").power(3), frame=start, per_origin=True)
    return out.select(key("origin").alias("event"), key("pos").alias("third"))


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS value, count(*) AS times FROM events GROUP BY 1")
def map_entries(g: Graphs) -> DataFrame:
    start = g.events().vertices("event").select(F.col("vid").alias("pos"))
    walk = HERE.out_edges("entry").keep("key", "=", "k").head().values("entry_value")
    return run(g.events(), g.spark, walk, frame=start).select("value", F.col("weight").alias("times"))


@query("SELECT 1 AS depth, count(*) AS vertices FROM nation UNION ALL SELECT 2, count(*) FROM customer JOIN nation ON n_nationkey = c_nationkey")
def geo_tree_descend(g: Graphs) -> DataFrame:
    """From the regions down, round by round, until nothing lies below."""
    graph = g.commerce()
    start = graph.vertices("region").select(F.col("vid").alias("pos"))
    met = run(graph, g.spark, HERE.repeat(HERE.into("in_region", "in_nation"), emit="all", max_depth=100), frame=start)
    depth = F.when(F.shiftright("pos", KEY_BITS) == NATION, 1).otherwise(2)
    return met.groupBy(depth.alias("depth")).agg(F.sum("weight").alias("vertices"))


# -- paths, sampling, other layouts

@query(
    f"""WITH {FRIEND} SELECT a.src || '>' || a.dst || '>' || b.dst AS path FROM friend a JOIN friend b ON b.src = a.dst WHERE a.src = 7 AND b.dst <> 7"""
)
def paths_two_hop(g: Graphs) -> DataFrame:
    out = run(g.commerce(), g.spark, recommend.friend_of_friend().simple_path(), ids(CUSTOMER, ME), mode="paths")
    stops = F.filter("path", lambda p: p["kind"] == "V")
    return out.select(F.array_join(F.transform(stops, lambda p: key_of(p["id"]).cast("string")), ">").alias("path"))


SAMPLED = "\nUNION ALL ".join(
    f"""SELECT {x} AS share, (SELECT count(*) FROM (SELECT part FROM s WHERE lot < {int(x * 1_000_000)} GROUP BY part ORDER BY sum(shared) DESC, part LIMIT 10) JOIN top USING (part)) / 10 AS recall,
round((SELECT coalesce(sum(shared), 0) FROM s WHERE lot < {int(x * 1_000_000)}) / {x}::DOUBLE / (SELECT sum(weight) FROM cf) - 1, 6) AS error"""
    for x in (0.25, 0.5, 0.75, 1.0)
)


@query(
    f"""{CF}, s AS (SELECT dst AS part, shared, CAST('0x' || substr(md5(concat_ws(':', (1::BIGINT << 56) + customer, 1)), 1, 12) AS BIGINT) % 1000000 AS lot FROM people JOIN likes ON src = customer),
top AS (SELECT part FROM cf ORDER BY weight DESC, part LIMIT 10) SELECT CAST(share AS DOUBLE) AS share, CAST(recall AS DOUBLE) AS recall, CAST(error AS DOUBLE) AS error FROM ({SAMPLED})"""
)
def sampled_cf_recall(g: Graphs) -> DataFrame:
    """Recall of the top 10 and relative error of the total when only a share of the people is walked through."""
    me, graph = ids(CUSTOMER, ME), g.commerce()
    exact = run(graph, g.spark, recommend.collaborative(), me)
    top = exact.orderBy(F.desc("weight"), "pos").limit(10).select("pos")
    out = None
    for share in (0.25, 0.5, 0.75, 1.0):
        some = run(graph, g.spark, recommend.similar_people().sample(share, 1) >> recommend.liked(), me)
        found = some.orderBy(F.desc("weight"), "pos").limit(10).join(top, "pos", "left_semi").agg(F.count("*").alias("hits"))
        weight = some.agg(F.coalesce(F.sum("weight"), F.lit(0)).alias("w")).crossJoin(exact.agg(F.sum("weight").alias("all")))
        one = found.crossJoin(weight).select(F.lit(share).alias("share"), (F.col("hits") / 10).alias("recall"), F.round(F.col("w") / F.lit(share) / F.col("all") - 1, 6).alias("error"))
        out = one if out is None else out.unionByName(one)
    return out


def _choice(n: int, before: str, near: str, far: str, seed: int) -> str:
    """One step of the seeded walk: of each walker's edges the one with the least md5 of edge id, origin and seed."""
    return (
        f"w{n} AS (SELECT o, {far} AS pos FROM (SELECT w.o, e.{far}, row_number() OVER (PARTITION BY w.o ORDER BY md5(concat_ws(':', e.eid, w.o, {seed})), e.eid) AS r FROM {before} w JOIN e ON e.{near} = w.pos) WHERE r = 1)"
    )


@query(
    f"""WITH {LIKES}, e AS (SELECT (1::BIGINT << 56) + src AS src, (2::BIGINT << 56) + dst AS dst, row_number() OVER (ORDER BY src, dst) - 1 AS eid FROM likes),
w0 AS (SELECT (1::BIGINT << 56) + c_custkey AS o, (1::BIGINT << 56) + c_custkey AS pos FROM customer), {_choice(1, "w0", "src", "dst", 11)}, {_choice(2, "w1", "dst", "src", 12)}, {_choice(3, "w2", "src", "dst", 13)}
SELECT pos - (2::BIGINT << 56) AS part, count(*) AS visits FROM w3 GROUP BY 1"""
)
def random_walk_visits(g: Graphs) -> DataFrame:
    """Every customer takes one pseudo-random liked part, then one of its likers, then one of that one's parts: fixed-length seeded walks, each with its own choices."""
    walk = HERE.sample_out("likes", 1, 11).sample_in("likes", 1, 12).sample_out("likes", 1, 13)
    ends = run(g.commerce(), g.spark, walk, frame=all_customers(g), per_origin=True)
    return ends.groupBy(key("pos").alias("part")).agg(F.sum("weight").alias("visits"))


@query(f"WITH {LIKES} SELECT dst AS part, count(*) AS times FROM likes WHERE src = 7 GROUP BY 1")
def single_relational_walk(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce().single("likes"), g.spark, HERE.out(), ids(CUSTOMER, ME)), "part")


@query(f"WITH {FRIEND}, s AS (SELECT dst FROM friend WHERE src = 7 UNION ALL SELECT dst FROM likes WHERE src = 7 UNION ALL SELECT o_orderkey FROM orders WHERE o_custkey = 7 UNION ALL SELECT c_nationkey FROM customer WHERE c_custkey = 7) SELECT (SELECT count(*) FROM s) AS edges_read, (SELECT count(*) FROM friend WHERE src = 7) AS edges_kept")
def unlabelled_layout_walk(g: Graphs) -> DataFrame:
    """Without a label index all k + x edges of the start are read; the filter comes late (rewriting is off)."""
    e = run(g.commerce(), g.spark, HERE.out_edges(*MIXED), ids(CUSTOMER, ME), rewrite=False)
    return e.agg(F.count("*").alias("edges_read"), F.count_if(F.col("label") == "friend").alias("edges_kept"))


@query(f"WITH {FRIEND} SELECT c_name AS value, count(*) AS times, CAST(5 * count(*) AS BIGINT) AS cells_read FROM friend JOIN customer ON c_custkey = dst WHERE src = 7 GROUP BY 1")
def generic_property_walk(g: Graphs) -> DataFrame:
    """Without a property index all y properties of each of the k vertices are examined: the long form of the property map."""
    c = g.commerce().vertices("customer")
    names = g.commerce().classes["customer"].keys
    bag = c.select("vid", F.explode(F.create_map(*[x for k in names for x in (F.lit(k), F.col(k).cast("string"))])).alias("key", "cell"))
    friends = run(g.commerce(), g.spark, HERE.out("friend"), ids(CUSTOMER, ME))
    read = friends.join(bag, friends.pos == bag.vid).groupBy("pos").agg(F.max(F.when(F.col("key") == "c_name", F.col("cell"))).alias("value"), F.max("weight").alias("w"), F.count("*").alias("cells"))
    return read.groupBy("value").agg(F.sum("w").alias("times"), F.sum("cells").alias("cells_read"))


@query(f"{CF} SELECT part, weight FROM cf")
def matrix_walk_cf(g: Graphs) -> DataFrame:
    out = baseline.matrix_walk(g.commerce(), g.spark, [("likes", "out"), ("likes", "in"), ("likes", "out")], ids(CUSTOMER, ME), clear_start_after=2)
    return keyed(out, "part", "weight")


@query(f"{CF} SELECT part, weight FROM cf ORDER BY weight DESC, part LIMIT 10")
def walk_text_frontend(g: Graphs) -> DataFrame:
    return keyed(run(g.commerce(), g.spark, parse_walk("mark me /likes> /<likes !me /likes> rank 10"), ids(CUSTOMER, ME)), "part", "weight")


@query(None)
def walk_design_cost(g: Graphs) -> DataFrame:
    """Hops, property lookups, set operations and exchanges of the library's walks, after rewriting."""
    rows = []
    for name, walk in recommend.LIBRARY.items():
        better, fired = optimize(walk, g.commerce())
        start = ids(PART if name == "content" else CUSTOMER, 3)
        c = cost(better)
        rows.append((name, c["hops"], c["lookups"], c["set_ops"], exchanges(g.commerce(), g.spark, walk, start), ",".join(sorted(set(fired)))))
    return g.spark.createDataFrame(rows, "walk string, hops int, lookups int, set_ops int, exchanges int, rules string")


@query(f"WITH {PEOPLE} SELECT c_mktsegment AS value, {total('shared')} AS times FROM people JOIN customer ON c_custkey = customer GROUP BY 1")
def group_count_segments(g: Graphs) -> DataFrame:
    """Segments of similar people, each person as often as likes are shared."""
    people = run(g.commerce(), g.spark, recommend.similar_people(), ids(CUSTOMER, ME))
    return reduce.group_count(g.commerce(), people, "c_mktsegment")


@query(f"WITH {PEOPLE} SELECT {total('shared')} AS traversers, count(*) AS places FROM people")
def count_traversers(g: Graphs) -> DataFrame:
    return reduce.count(run(g.commerce(), g.spark, recommend.similar_people(), ids(CUSTOMER, ME)))


@query("SELECT 'nation' AS vclass, n_name AS name FROM nation UNION ALL SELECT 'region', r_name FROM region")
def generic_vertex_view(g: Graphs) -> DataFrame:
    """The dynamic view: one VARIANT bag of properties for every class."""
    graph = g.commerce()
    graph.classes = {k: graph.classes[k] for k in ("nation", "region")}
    v = graph.generic_vertices()
    return v.select("vclass", F.coalesce(F.try_variant_get("props", "$.n_name", "string"), F.try_variant_get("props", "$.r_name", "string")).alias("name"))


# -- measures

DEG = f"WITH {FRIEND}, k AS (SELECT src, count(*) AS k FROM friend GROUP BY 1), x AS (SELECT src, count(*) AS x FROM likes GROUP BY 1), p AS (SELECT c_custkey AS person, coalesce(k, 0) AS k, coalesce(x, 0) AS x, (SELECT count(*) FROM customer)::DOUBLE AS n FROM customer LEFT JOIN k ON k.src = c_custkey LEFT JOIN x ON x.src = c_custkey)"


def _degrees(g: Graphs) -> DataFrame:
    graph = g.commerce()
    people = graph.vertices("customer").select("vid", F.col("c_custkey").alias("person"))
    k, x = graph.degrees("friend").withColumnsRenamed({"vid": "kv", "degree": "k"}), graph.degrees("likes").withColumnsRenamed({"vid": "xv", "degree": "x"})
    n = people.agg(F.count("*").alias("n"))
    joined = people.join(k, people.vid == k.kv, "left").join(x, people.vid == x.xv, "left").crossJoin(F.broadcast(n))
    return joined.select("person", F.coalesce("k", F.lit(0)).alias("k"), F.coalesce("x", F.lit(0)).alias("x"), "n")


@query(f"{DEG} SELECT person, k, x, round(log2(n), 6) AS term1, 1.0::DOUBLE AS term2, round(log2(greatest(k, 1)::DOUBLE), 6) AS term3, k::DOUBLE AS term4, round(k * log2(n), 6) AS term5, k::DOUBLE AS term6, round(log2(n) + 1 + log2(greatest(k, 1)::DOUBLE) + k + k * log2(n) + k, 6) AS total FROM p")
def cost_relational(g: Graphs) -> DataFrame:
    d = _degrees(g)
    return measures.with_total(d, measures.relational_cost(F.col("n"), F.col("k"), F.col("k"))).drop("n")


@query(f"{DEG} SELECT person, k, x, round(log2(n), 6) AS term1, (k + x)::DOUBLE AS term2, k::DOUBLE AS term3, (k * 5)::DOUBLE AS term4, round(log2(n) + k + x + k + k * 5, 6) AS total FROM p")
def cost_walk(g: Graphs) -> DataFrame:
    return measures.with_total(_degrees(g), measures.walk_cost(F.col("n"), F.col("k"), F.col("x"), 5)).drop("n")


TOUCHED = f"""{PEOPLE}, t0 AS (SELECT dst FROM likes WHERE src = 7), t1 AS (SELECT b.src, count(*) AS w FROM t0 JOIN likes b ON b.dst = t0.dst GROUP BY 1),
t2 AS (SELECT count(*) AS p, {total("shared")} AS w FROM people), t3 AS (SELECT dst, {total("shared")} AS w FROM people JOIN likes ON src = customer GROUP BY 1)"""


@query(
    f"""WITH {TOUCHED} SELECT 'liked' AS step, (SELECT count(*) FROM t0) AS positions, (SELECT count(*) FROM t0) AS weight
UNION ALL SELECT 'likers', count(*), {total("w")} FROM t1 UNION ALL SELECT 'others', p, w FROM t2 UNION ALL SELECT 'resources', count(*), {total("w")} FROM t3"""
)
def touched_elements(g: Graphs) -> DataFrame:
    names = {2: "liked", 4: "likers", 5: "others", 7: "resources"}
    all_steps = touched(g.commerce(), g.spark, recommend.collaborative(), ids(CUSTOMER, ME))
    named_steps = F.element_at(F.create_map(*[x for k, v in names.items() for x in (F.lit(k), F.lit(v))]), F.col("step"))
    return all_steps.where(F.col("step").isin(*names)).select(named_steps.alias("step"), "positions", "weight")


COUNTERS = f"""{TOUCHED}, n AS (SELECT count(*) AS k FROM t0), f(step, op, positions, weight, edges, cells) AS (
SELECT 1, 'edges to resources', (SELECT k FROM n), (SELECT k FROM n), (SELECT k FROM n), 0 UNION ALL SELECT 3, 'edges to people', (SELECT {total("w")} FROM t1), (SELECT {total("w")} FROM t1), (SELECT {total("w")} FROM t1), 0
UNION ALL SELECT 4, 'people', (SELECT count(*) FROM t1), (SELECT {total("w")} FROM t1), 0, 0
UNION ALL SELECT 6, 'edges to their resources', (SELECT count(*) FROM people JOIN likes ON src = customer), (SELECT {total("w")} FROM t3), (SELECT count(*) FROM people JOIN likes ON src = customer), 0
UNION ALL SELECT 7, 'their resources', (SELECT count(*) FROM t3), (SELECT {total("w")} FROM t3), 0, 0
UNION ALL SELECT 8, 'brands', (SELECT count(DISTINCT p_brand) FROM t3 JOIN part ON p_partkey = dst), (SELECT {total("w")} FROM t3), 0, (SELECT count(*) FROM t3))"""
_STEPS = {1: "edges to resources", 3: "edges to people", 4: "people", 6: "edges to their resources", 7: "their resources", 8: "brands"}


def _counters(g: Graphs, graph: PropertyGraph) -> DataFrame:
    walk = recommend.collaborative().values("p_brand")
    named_steps = F.element_at(F.create_map(*[x for k, v in _STEPS.items() for x in (F.lit(k), F.lit(v))]), F.col("step"))
    counted = touched(graph, g.spark, walk, ids(CUSTOMER, ME)).where(F.col("step").isin(*_STEPS))
    return counted.select("step", named_steps.alias("op"), "positions", "weight", "edges", "cells")


@query(f"WITH {COUNTERS} SELECT step, op, CAST(positions AS BIGINT) AS positions, CAST(weight AS BIGINT) AS weight, CAST(edges AS BIGINT) AS edges, CAST(cells AS BIGINT) AS cells FROM f")
def touched_counters(g: Graphs) -> DataFrame:
    """Positions, weight, edges scanned and property cells of each step of the collaborative walk, brands read at its end."""
    return _counters(g, g.commerce())


def padded(graph: PropertyGraph, labels: list[str], copies: int) -> PropertyGraph:
    """The graph with unrelated copies of the labels' edges beside them: a larger database around the same neighbourhoods."""

    def more(x: EdgeLabel) -> EdgeLabel:
        def rows(side) -> DataFrame:
            shifted = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy")
            e = side().select("eid", "src", "dst", *x.keys, shifted)
            far = F.col("copy").cast("long") * F.lit(1 << 40)
            return e.select(*[(F.col(c) + far).alias(c) for c in ("eid", "src", "dst")], *x.keys)

        return EdgeLabel(x.name, lambda: rows(x.rows), x.keys, by_head=lambda: rows(x.by_head or x.rows))

    return PropertyGraph.of(list(graph.classes.values()), [more(graph.labels[x]) for x in labels])


@query(f"WITH {COUNTERS} SELECT copies, step, CAST(positions AS BIGINT) AS positions, CAST(edges AS BIGINT) AS edges, CAST(cells AS BIGINT) AS cells, copies * (SELECT count(*) FROM likes) AS all_edges FROM f, (VALUES (1), (2), (4)) c(copies)")
def padding_touched(g: Graphs) -> DataFrame:
    """What a walk touches while unrelated copies of the graph make it 1, 2 and 4 times as large: the same."""
    out = None
    for copies in (1, 2, 4):
        graph = padded(g.commerce(), ["likes"], copies)
        n = graph.edges("likes").agg(F.count("*").alias("all_edges"))
        one = _counters(g, graph).crossJoin(F.broadcast(n)).select(F.lit(copies).alias("copies"), "step", "positions", "edges", "cells", "all_edges")
        out = one if out is None else out.unionByName(one)
    return out


@query(f"{CF} SELECT copies, count(*) AS positions, {total('weight')} AS weight FROM cf, (VALUES (1), (2)) c(copies) GROUP BY 1")
def padding_invariance(g: Graphs) -> DataFrame:
    """An unrelated copy of the graph beside it leaves the walk's result unchanged; `padding_touched` counts its work."""
    out = None
    for copies in (1, 2):
        one = run(padded(g.commerce(), ["likes"], copies), g.spark, recommend.collaborative(), ids(CUSTOMER, ME)).agg(F.count("*").alias("positions"), F.sum("weight").alias("weight"))
        one = one.select(F.lit(copies).alias("copies"), "positions", "weight")
        out = one if out is None else out.unionByName(one)
    return out


@query(
    f"""WITH {FRIEND}, k AS (SELECT count(*) AS k FROM friend WHERE src = 7), x AS (SELECT count(*) AS x FROM likes WHERE src = 7), n AS (SELECT count(*) AS n FROM customer), m AS (SELECT count(*) AS m FROM friend)
SELECT copies, copies * n AS persons, copies * m AS friend_rows, k AS names, copies * (2 * n + m) AS rows_joined, round(log2(copies * n) + 1 + log2(greatest(k, 1)::DOUBLE) + k + k * log2(copies * n) + k, 6) AS relational_cost,
k AS edges_walked, round(log2(copies * n) + k + x + k + 5 * k, 6) AS walk_cost FROM k, x, n, m, (VALUES (1), (2), (4)) c(copies)"""
)
def join_cost_growth(g: Graphs) -> DataFrame:
    """The same neighbourhood in databases of 1, 2 and 4 times the size: the rows that the join plan's three inputs hold and its logarithmic costs grow,
    the edges that the walk reads do not."""
    c, out, shift = g.table("customer"), None, 1 << 40
    likes = run(g.commerce(), g.spark, HERE.out_edges("likes"), ids(CUSTOMER, ME)).agg(F.count("*").alias("x"))
    for copies in (1, 2, 4):
        graph = padded(g.commerce(), ["friend"], copies)
        many = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy")
        person = c.select("c_custkey", "c_name", many).select((F.col("c_custkey") + F.col("copy").cast("long") * shift).alias("c_custkey"), F.when(F.col("copy") == 0, F.col("c_name")).otherwise(F.concat("c_name", F.lit("#"), "copy")).alias("c_name"))
        friend = graph.edges("friend").select(key("src").alias("src"), key("dst").alias("dst"))
        names = baseline.relational_friend_names(g.spark, person, friend, NAME).agg(F.coalesce(F.sum("times"), F.lit(0)).alias("names"))
        walked = touched(graph, g.spark, HERE.out("friend"), ids(CUSTOMER, ME)).agg(F.sum("edges").alias("edges_walked"))
        sizes = person.agg(F.count("*").alias("persons")).crossJoin(F.broadcast(friend.agg(F.count("*").alias("friend_rows"))))
        one = sizes.crossJoin(F.broadcast(names)).crossJoin(F.broadcast(walked)).crossJoin(F.broadcast(likes))  # one row each
        n, k, x = F.col("persons"), F.col("names"), F.col("x")
        cost_of = lambda terms: F.round(sum(terms.values(), F.lit(0.0)), 6)
        one = one.select(
            F.lit(copies).alias("copies"), "persons", "friend_rows", "names", (2 * n + F.col("friend_rows")).alias("rows_joined"),
            cost_of(measures.relational_cost(n, k, k)).alias("relational_cost"), "edges_walked", cost_of(measures.walk_cost(n, k, x, 5)).alias("walk_cost"),
        )
        out = one if out is None else out.unionByName(one)
    return out


@query(
    f"""WITH {LIKES}, o AS (SELECT src, count(*) AS d FROM likes GROUP BY 1), i AS (SELECT dst, count(*) AS d, {total("o.d")} AS two FROM likes JOIN o USING (src) GROUP BY 1)
SELECT CAST(floor(log2(d)) AS BIGINT) AS degree_octave, count(*) AS starts, {total("d")} AS one_hop, {total("two")} AS two_hops, round(sum(d) / count(*), 6) AS per_start FROM i GROUP BY 1"""
)
def supernode_cost(g: Graphs) -> DataFrame:
    """Edges that one and two hops from a part touch, by the octave of its degree: the cost follows the local degree."""
    graph = g.commerce()
    start = graph.vertices("part").select(F.col("vid").alias("pos"))
    one = run(graph, g.spark, HERE.in_edges("likes").head(), frame=start, per_origin=True).groupBy("origin").agg(F.sum("weight").alias("d"))
    two = run(graph, g.spark, HERE.into("likes").out_edges("likes").tail(), frame=start, per_origin=True).groupBy("origin").agg(F.sum("weight").alias("two"))
    octave = F.floor(F.log2(F.col("d").cast("double")))
    sums = one.join(two, "origin").groupBy(octave.alias("degree_octave"))
    return sums.agg(F.count("*").alias("starts"), F.sum("d").alias("one_hop"), F.sum("two").alias("two_hops"), F.round(F.sum("d") / F.count("*"), 6).alias("per_start"))


@query(
    f"""WITH {FRIEND}, {FEATURE}, e AS (SELECT 'likes' AS label, src FROM likes UNION ALL SELECT 'feature', src FROM feature UNION ALL SELECT 'friend', src FROM friend),
d AS (SELECT label, src, count(*) AS d FROM e GROUP BY 1, 2)
SELECT label, count(*) AS vertices, {total("d")} AS edges, max(d) AS max_degree, CAST(median(d) AS DOUBLE) AS median_degree, round(avg(d), 6) AS mean_degree, first(src ORDER BY d DESC, src) AS max_vertex FROM d GROUP BY 1"""
)
def degree_profile(g: Graphs) -> DataFrame:
    out = None
    for label in ("likes", "feature", "friend"):
        one = measures.degree_profile(g.commerce().edges(label), label).withColumn("max_vertex", key("max_vertex"))
        out = one if out is None else out.unionByName(one)
    return out


@query(f"WITH {FEATURE} SELECT dst AS feature, count(*) AS degree FROM feature GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10")
def supernodes(g: Graphs) -> DataFrame:
    d = g.commerce().degrees("feature", "in")
    names = g.commerce().vertices("feature")
    return d.join(names, "vid").select("feature", "degree").orderBy(F.desc("degree"), "feature").limit(10)


@query(f"WITH {FRIEND} SELECT 'likes' AS label, count(*) FILTER (WHERE src % 16 <> dst % 16) AS cut, count(*) AS total FROM likes UNION ALL SELECT 'friend', count(*) FILTER (WHERE src % 16 <> dst % 16), count(*) FROM friend")
def edge_cut_ratio(g: Graphs) -> DataFrame:
    out = None
    for label in ("likes", "friend"):
        e = g.commerce().edges(label).select(key("src").alias("src"), key("dst").alias("dst"))
        one = measures.cut_ratio(e, 16, label)
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT doc_id AS doc, lang, n_chars FROM documents WHERE doc_id = 7")
def flat_lookup(g: Graphs) -> DataFrame:
    return baseline.flat_lookup(g.table("documents"), "doc_id", 7).select(F.col("doc_id").alias("doc"), "lang", "n_chars")


@query(f"WITH {LIKES}, p AS (SELECT a.src AS customer, b.src AS other, count(*) AS shared FROM likes a JOIN likes b ON b.dst = a.dst AND b.src <> a.src GROUP BY 1, 2) SELECT other AS customer, shared FROM p WHERE customer = 7")
def global_pass_then_filter(g: Graphs) -> DataFrame:
    """The set-based contrast: all pairs are made and stored first, one origin is picked afterwards."""
    pairs = stored(recommend.shared_pairs(g.commerce().edges("likes")), "global-pass")
    return pairs.where(F.col("a") == F.lit(ids(CUSTOMER, ME)[0])).select(key("b").alias("customer"), F.col("weight").alias("shared"))


@query(
    f"""WITH {LIKES}, p AS (SELECT a.src AS a, b.src AS b FROM likes a JOIN likes b ON b.dst = a.dst AND b.src <> a.src GROUP BY 1, 2)
SELECT (SELECT count(*) FROM p) AS pairs_made, (SELECT count(*) FROM p WHERE a = 7) AS pairs_kept, (SELECT count(*) FROM likes a JOIN likes b ON b.dst = a.dst WHERE a.src = 7) + (SELECT count(*) FROM likes WHERE src = 7) AS edges_walked"""
)
def global_pass_cost(g: Graphs) -> DataFrame:
    """Pairs that the global pass makes for one origin's answer, beside the edges that the local walk reads for the same."""
    pairs = stored(recommend.shared_pairs(g.commerce().edges("likes")), "global-pass")
    made = pairs.agg(F.count("*").alias("pairs_made"), F.count_if(F.col("a") == F.lit(ids(CUSTOMER, ME)[0])).alias("pairs_kept"))
    return made.crossJoin(F.broadcast(touched(g.commerce(), g.spark, recommend.similar_people(), ids(CUSTOMER, ME)).agg(F.sum("edges").alias("edges_walked"))))


@query(f"WITH {FEATURE} SELECT part, count(*) AS neighbours, CAST(sum(n) AS BIGINT) AS shares FROM (SELECT a.src AS part, b.src AS o, count(*) AS n FROM feature a JOIN feature b ON b.dst = a.dst AND b.src <> a.src GROUP BY 1, 2) GROUP BY 1")
def content_signature_quotient(g: Graphs) -> DataFrame:
    """Neighbours and content shares of every part, by signatures and their member counts."""
    return recommend.signature_totals(g.commerce().edges("feature")).select(key("a").alias("part"), "neighbours", "shares")


@query(f"WITH {LIKES} SELECT src AS customer, count(*) AS weight FROM likes WHERE src IN (7, 8, 9) GROUP BY 1")
def roundtrip_degree(g: Graphs) -> DataFrame:
    """Out-edges then tail: a degree lookup, not a join of edges (rewritten)."""
    return keyed(run(g.commerce(), g.spark, HERE.out_edges("likes").tail(), ids(CUSTOMER, 7, 8, 9)), "customer", "weight")


@query(f"WITH {LIKES} SELECT DISTINCT src AS customer FROM likes WHERE dst IN (3, 5)")
def reversed_walk(g: Graphs) -> DataFrame:
    """Who can reach parts 3 or 5 by likes: the end is bound, so the walk runs backwards from it."""
    from ..plans.rewrite import reverse_walk

    return keyed(run(g.commerce(), g.spark, reverse_walk(recommend.liked()).dedup(), ids(PART, 3, 5)), "customer", None)


@query(f"{BOTH} SELECT part, least(cf.weight, content.weight) AS weight FROM cf JOIN content USING (part)")
def walks_intersect(g: Graphs) -> DataFrame:
    a, b = (df for df, _ in _both(g))
    return a.join(b.select("pos", F.col("weight").alias("_w")), "pos").select(key("pos").alias("part"), F.least("weight", "_w").alias("weight"))


NEAR = f"WITH {FRIEND}, people AS (SELECT b.src AS customer, count(*) AS shared FROM likes a JOIN likes b ON b.dst = a.dst AND b.src <> a.src WHERE a.src = 7 GROUP BY 1), arm AS (SELECT dst AS customer, {total('shared')} AS w FROM people JOIN friend ON src = customer GROUP BY 1)"


@query(f"{NEAR} SELECT customer, least(shared, w) AS weight FROM people JOIN arm USING (customer)")
def walk_intersect_steps(g: Graphs) -> DataFrame:
    """Similar people who are also friends of similar people: the lesser multiplicity, as a step of one walk."""
    walk = recommend.similar_people().intersect(HERE.out("friend"))
    return keyed(run(g.commerce(), g.spark, walk, ids(CUSTOMER, ME)), "customer", "weight")


@query(f"WITH {PEOPLE} SELECT 'multiset' AS form, customer, shared - 1 AS weight FROM people WHERE shared > 1 UNION ALL SELECT 'distinct', customer, shared FROM people JOIN customer ON c_custkey = customer WHERE c_mktsegment <> 'BUILDING'")
def walk_minus_steps(g: Graphs) -> DataFrame:
    """Similar people less one traverser each, by multiplicities; and less those of one segment, by places."""
    out = None
    for form, arm in (("multiset", HERE.unit()), ("distinct", HERE.keep("c_mktsegment", "=", "BUILDING"))):
        walk = recommend.similar_people().minus(arm, distinct=form == "distinct")
        one = keyed(run(g.commerce(), g.spark, walk, ids(CUSTOMER, ME)), "customer", "weight").select(F.lit(form).alias("form"), "customer", "weight")
        out = one if out is None else out.unionByName(one)
    return out


@query(f"{BOTH} SELECT part, {total('weight')} AS weight FROM (SELECT * FROM cf UNION ALL SELECT * FROM content) GROUP BY 1")
def hybrid_walk_one_plan(g: Graphs) -> DataFrame:
    """Content and collaborative recommendation as two arms of one walk, merged by position."""
    walk = HERE.overlay(recommend.collaborative(), recommend.content_by_likes())
    return keyed(run(g.commerce(), g.spark, walk, ids(CUSTOMER, ME)), "part", "weight")


@query(f"{CF} SELECT part, weight FROM cf")
def layout_walk(g: Graphs) -> DataFrame:
    """The collaborative walk over a layout that was written and read back: hops out from files by tail, hops in from files by head."""
    path = f"{shared_dir(g.spark)}/pathflow-graph/layout-{uuid.uuid4().hex}"
    g.commerce().single("likes").write_layout(path, 8)
    return keyed(run(PropertyGraph.from_layout(g.spark, path, ["likes"]), g.spark, recommend.collaborative(), ids(CUSTOMER, ME)), "part", "weight")
