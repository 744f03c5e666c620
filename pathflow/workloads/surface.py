"""Surrounding surface: joins, aggregation, windows, sets, functions, UDFs, formats. Not part of the method; for its users."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.regions import overlaps
from ..plans.lower import run
from ..plans.traversal import HERE
from ..sources.graph import key_of
from ..sources.scratch import shared_dir
from ..sources.tables import json_property, read_edge_list, write_result
from .graphs import CUSTOMER, Graphs
from .registry import query
from .regions import PLANE, part_tree
from .walks import FEATURE, LIKES, PEOPLE, ids, key, keyed


@query(f"WITH {LIKES} SELECT f AS format, (SELECT count(*) FROM likes) AS edges, (SELECT CAST(sum(src * 31 + dst) AS BIGINT) FROM likes) AS checksum FROM (VALUES ('csv'), ('json'), ('orc'), ('parquet'), ('text')) t(f)")
def scan_formats_roundtrip(g: Graphs) -> DataFrame:
    """All edges go through each format and back."""
    edges = g.commerce().edges("likes").select(key("src").alias("src"), key("dst").alias("dst"))
    base, out = f"{shared_dir(g.spark)}/pathflow-graph/formats-{uuid.uuid4().hex}", None
    for fmt in ("csv", "json", "orc", "parquet", "text"):
        write_result(edges, f"{base}/{fmt}", fmt)
        back = read_edge_list(g.spark, f"{base}/{fmt}", fmt)
        one = back.agg(F.count("*").alias("edges"), F.sum(F.col("src") * 31 + F.col("dst")).alias("checksum")).select(F.lit(fmt).alias("format"), "edges", "checksum")
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, json_extract(props, '$.none') IS NULL AS missing, count(*) AS n FROM events GROUP BY 1, 2")
def fn_json_props(g: Graphs) -> DataFrame:
    e = g.table("events").select(json_property("props", "k", "long").alias("k"), json_property("props", "none", "string").isNull().alias("missing"))
    return e.groupBy("k", "missing").agg(F.count("*").alias("n"))


@query("SELECT p_partkey AS part FROM part WHERE p_size BETWEEN 10 AND 20 AND p_brand IN ('Brand#1', 'Brand#2', 'Brand#3') AND p_name LIKE 'r%' AND p_type IS NOT NULL AND p_type IS DISTINCT FROM 'SMALL'")
def filter_predicates(g: Graphs) -> DataFrame:
    p = g.table("part")
    keep = F.col("p_size").between(10, 20) & F.col("p_brand").isin("Brand#1", "Brand#2", "Brand#3") & F.col("p_name").like("r%") & F.col("p_type").isNotNull() & ~F.col("p_type").eqNullSafe("SMALL")
    return p.where(keep).select(F.col("p_partkey").alias("part"))


@query("SELECT h AS strategy, count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS s FROM orders JOIN customer ON c_custkey = o_custkey, (VALUES ('broadcast'), ('merge'), ('shuffle_hash')) t(h) WHERE c_nationkey = 3 GROUP BY 1")
def join_strategies(g: Graphs) -> DataFrame:
    """One equi-join by hash broadcast (of 1/25 of the customers, by statistics), sort-merge and shuffled hash."""
    few, out = g.table("customer").where("c_nationkey = 3").select("c_custkey"), None
    orders = g.table("orders").select("o_orderkey", "o_custkey")
    for hint in ("broadcast", "merge", "shuffle_hash"):
        side = few if hint == "broadcast" else few.hint(hint)  # the optimiser broadcasts by size
        one = orders.join(side, orders.o_custkey == side.c_custkey).agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("s")).select(F.lit(hint).alias("strategy"), "n", "s")
        out = one if out is None else out.unionByName(one)
    return out


@query("WITH r AS (SELECT i AS rect, i * 10.0 AS x0, i * 10.0 + 5 AS x1 FROM range(0, 10) t(i)) SELECT rect, n_nationkey AS nation FROM r CROSS JOIN nation WHERE n_nationkey * 4 BETWEEN x0 AND x1")
def join_cross_rects(g: Graphs) -> DataFrame:
    rects = g.spark.range(10).select(F.col("id").alias("rect"), (F.col("id") * 10.0).alias("x0"), (F.col("id") * 10.0 + 5).alias("x1"))
    n = g.table("nation").select(F.col("n_nationkey").alias("nation"))  # 25 rows by definition
    return n.crossJoin(F.broadcast(rects)).where((F.col("nation") * 4).between(F.col("x0"), F.col("x1"))).select("rect", "nation")


@query("WITH r AS (SELECT i AS band, 900 + i * 10.0 AS lo, 905 + i * 10.0 AS hi FROM range(0, 10) t(i)) SELECT band, count(*) AS parts FROM r JOIN part ON p_retailprice BETWEEN lo AND hi GROUP BY 1")
def join_range_regions(g: Graphs) -> DataFrame:
    """A range join as an equi-join: bands are exploded to unit bins, rows fall into one bin, the exact test follows."""
    bands = g.spark.range(10).select(F.col("id").alias("band"), (F.col("id") * 10.0 + 900).alias("lo"), (F.col("id") * 10.0 + 905).alias("hi"))
    binned = bands.withColumn("bin", F.explode(F.sequence(F.floor("lo"), F.floor("hi"))))
    p = g.table("part").select("p_retailprice", F.floor("p_retailprice").alias("bin"))
    return p.join(binned, "bin").where(F.col("p_retailprice").between(F.col("lo"), F.col("hi"))).groupBy("band").agg(F.count("*").alias("parts"))


KNOWN = f"WITH {PEOPLE}, cf AS (SELECT dst AS part FROM people JOIN likes ON src = customer GROUP BY 1) SELECT part FROM cf WHERE part {{}} IN (SELECT dst FROM likes WHERE src = 7)"


def _known(g: Graphs, how: str) -> DataFrame:
    from ..operators.recommend import collaborative, liked

    all_parts = run(g.commerce(), g.spark, collaborative(), ids(CUSTOMER, 7))
    known = run(g.commerce(), g.spark, liked(), ids(CUSTOMER, 7)).select("pos")
    return keyed(all_parts.join(known, "pos", how), "part", None)


@query(KNOWN.format(""))
def join_semi_known(g: Graphs) -> DataFrame:
    return _known(g, "left_semi")


@query(KNOWN.format("NOT"))
def join_anti_unknown(g: Graphs) -> DataFrame:
    return _known(g, "left_anti")


@query("WITH o AS (SELECT o_custkey AS k, count(*) AS orders FROM orders GROUP BY 1), e AS (SELECT user_id AS k, count(*) AS events FROM events GROUP BY 1) SELECT k AS customer, coalesce(orders, 0) AS orders, coalesce(events, 0) AS events FROM o FULL JOIN e USING (k)")
def join_full_degrees(g: Graphs) -> DataFrame:
    o = g.table("orders").groupBy(F.col("o_custkey").alias("customer")).agg(F.count("*").alias("orders"))
    e = g.table("events").groupBy(F.col("user_id").alias("customer")).agg(F.count("*").alias("events"))
    return o.join(e, "customer", "full").select("customer", F.coalesce("orders", F.lit(0)).alias("orders"), F.coalesce("events", F.lit(0)).alias("events"))


@query("SELECT p.event_id AS purchase, v.event_id AS view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF JOIN (SELECT * FROM events WHERE event_type = 'view') v ON v.user_id = p.user_id AND v.ts <= p.ts")
def join_asof_events(g: Graphs) -> DataFrame:
    """As-of join as one window: the last view at or before each purchase of a user. One shuffle, no pairs."""
    e = g.table("events").where("event_type IN ('purchase', 'view')")
    before = W.partitionBy("user_id").orderBy("ts", F.desc("event_type")).rowsBetween(W.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before)
    return e.withColumn("view", last).where("event_type = 'purchase' AND view IS NOT NULL").select(F.col("event_id").alias("purchase"), "view")


@query("SELECT v.event_id AS view, p.event_id AS purchase FROM events v JOIN events p ON p.user_id = v.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR")
def join_interval_events(g: Graphs) -> DataFrame:
    """Interval join on hour buckets: a view meets its own and the next bucket, then the exact test."""
    e = g.table("events").select("event_id", "user_id", "event_type", "ts", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600).alias("hour"))
    v = e.where("event_type = 'view'").select(F.col("event_id").alias("view"), "user_id", F.col("ts").alias("vts"), F.explode(F.array("hour", F.col("hour") + 1)).alias("hour"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("pts"), "hour")
    return v.join(p, ["user_id", "hour"]).where("pts >= vts AND pts <= vts + INTERVAL 1 HOUR").select("view", "purchase")


@query(f"WITH {FEATURE} SELECT src AS part, dst AS feature FROM feature")
def join_lateral_features(g: Graphs) -> DataFrame:
    words = "transform(split(p_name, ' '), w -> 'word:' || w)"
    return g.spark.sql(f"SELECT p_partkey AS part, feature FROM {{part}}, LATERAL (SELECT explode(concat(array('brand:' || p_brand, 'type:' || p_type, 'size:' || p_size), {words})) AS feature)", part=g.table("part"))


@query("SELECT event_type AS kind, count(*) AS edges FROM events GROUP BY 1 ORDER BY 2 DESC LIMIT 100")
def agg_approx_top_k(g: Graphs) -> DataFrame:
    """Heavy hitters by a bounded sketch; exact here, as there are fewer kinds than tracked items."""
    top = g.table("events").agg(F.expr("approx_top_k(event_type, 100, 10000)").alias("top"))
    return top.select(F.explode("top").alias("x")).select(F.col("x.item").alias("kind"), F.col("x.count").alias("edges"))


@query(f"WITH {LIKES} SELECT dst AS part, count(DISTINCT src) AS people FROM likes GROUP BY 1")
def agg_distinct(g: Graphs) -> DataFrame:
    return g.commerce().edges("likes_multi").groupBy(key("dst").alias("part")).agg(F.count_distinct("src").alias("people"))


@query(None)
def agg_approx_distinct(g: Graphs) -> DataFrame:
    e = g.commerce().edges("likes_multi")
    return e.agg(F.approx_count_distinct("src", 0.02).alias("people"), F.count_distinct("src").alias("exact"))


CUBED = f"WITH {LIKES} SELECT c_mktsegment AS segment, c_nationkey AS nation, count(*) AS likes FROM likes JOIN customer ON c_custkey = src GROUP BY"


def _segments(g: Graphs) -> DataFrame:
    c = g.table("customer").select((F.col("c_custkey") + (CUSTOMER << 56)).alias("src"), F.col("c_mktsegment").alias("segment"), F.col("c_nationkey").alias("nation"))
    return g.commerce().edges("likes").select("src").join(c, "src")


@query(f"{CUBED} CUBE (1, 2)")
def agg_cube_likes(g: Graphs) -> DataFrame:
    return _segments(g).cube("segment", "nation").agg(F.count("*").alias("likes"))


@query("SELECT r_name AS region, n_name AS nation, count(*) AS customers FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (1, 2)")
def agg_rollup_geo(g: Graphs) -> DataFrame:
    c = g.table("customer").join(g.table("nation"), F.col("n_nationkey") == F.col("c_nationkey")).join(g.table("region"), F.col("r_regionkey") == F.col("n_regionkey"))
    return c.rollup(F.col("r_name").alias("region"), F.col("n_name").alias("nation")).agg(F.count("*").alias("customers"))


@query(f"{CUBED} GROUPING SETS ((1), (2))")
def agg_grouping_sets(g: Graphs) -> DataFrame:
    return _segments(g).groupingSets([["segment"], ["nation"]], "segment", "nation").agg(F.count("*").alias("likes"))


EVENT_KINDS = ["click", "error", "purchase", "signup", "view"]


@query("SELECT user_id AS user, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{k}') AS n_{k}" for k in EVENT_KINDS) + " FROM events GROUP BY 1")
def agg_pivot_events(g: Graphs) -> DataFrame:
    p = g.table("events").groupBy(F.col("user_id").alias("user")).pivot("event_type", EVENT_KINDS).agg(F.count(F.lit(1)))
    return p.select("user", *[F.coalesce(F.col(k), F.lit(0)).alias(f"n_{k}") for k in EVENT_KINDS])


@query(
    """SELECT event_id AS event, rank() OVER w AS rnk, dense_rank() OVER w AS dense, CAST(ntile(4) OVER t AS BIGINT) AS quarter, round(percent_rank() OVER w, 6) AS share, round(cume_dist() OVER w, 6) AS upto,
round(sum(value) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last3, round(sum(value) OVER (PARTITION BY user_id ORDER BY value RANGE BETWEEN 5 PRECEDING AND CURRENT ROW), 4) AS near
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_type), t AS (PARTITION BY user_id ORDER BY ts)"""
)
def win_rank_frames(g: Graphs) -> DataFrame:
    w, t = W.partitionBy("user_id").orderBy("event_type"), W.partitionBy("user_id").orderBy("ts")
    near = W.partitionBy("user_id").orderBy("value").rangeBetween(-5, 0)
    return g.table("events").select(
        F.col("event_id").alias("event"), F.rank().over(w).cast("long").alias("rnk"), F.dense_rank().over(w).cast("long").alias("dense"), F.ntile(4).over(t).cast("long").alias("quarter"),
        F.round(F.percent_rank().over(w), 6).alias("share"), F.round(F.cume_dist().over(w), 6).alias("upto"), F.round(F.sum("value").over(t.rowsBetween(-2, 0)), 4).alias("last3"), F.round(F.sum("value").over(near), 4).alias("near"),
    )


@query("SELECT event_id AS event, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)")
def win_lead_lag(g: Graphs) -> DataFrame:
    w = W.partitionBy("user_id").orderBy("ts")
    return g.table("events").select(F.col("event_id").alias("event"), F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(w).alias("second"))


@query("SELECT p_partkey AS part, p_size AS size FROM part ORDER BY p_size DESC, p_partkey LIMIT 25")
def topk_ties(g: Graphs) -> DataFrame:
    return g.table("part").select(F.col("p_partkey").alias("part"), F.col("p_size").alias("size")).orderBy(F.desc("size"), "part").limit(25)


SETS = f"WITH {LIKES}, a AS (SELECT dst FROM likes WHERE src IN (7, 8)), b AS (SELECT dst FROM likes WHERE src IN (8, 9))"


def _two(g: Graphs) -> tuple[DataFrame, DataFrame]:
    parts = lambda *who: run(g.commerce(), g.spark, HERE.out("likes"), ids(CUSTOMER, *who), mode="rows").select(key("pos").alias("part"))
    return parts(7, 8), parts(8, 9)


@query(f"{SETS} SELECT dst AS part, count(*) AS times FROM (SELECT * FROM a UNION ALL SELECT * FROM b) GROUP BY 1")
def set_union_frontiers(g: Graphs) -> DataFrame:
    walk = HERE.overlay(HERE.out("likes"), HERE.drop_element(ids(CUSTOMER, 7)).out("likes"))
    out = run(g.commerce(), g.spark, walk, ids(CUSTOMER, 7, 8)).unionByName(run(g.commerce(), g.spark, HERE.out("likes"), ids(CUSTOMER, 9)))
    return out.groupBy(key("pos").alias("part")).agg(F.sum("weight").alias("times"))


@query(f"{SETS} SELECT dst AS part FROM a INTERSECT ALL SELECT dst FROM b")
def set_intersect_frontiers(g: Graphs) -> DataFrame:
    a, b = _two(g)
    return a.intersectAll(b)


@query(f"{SETS} SELECT dst AS part FROM a EXCEPT ALL SELECT dst FROM b")
def set_except_frontiers(g: Graphs) -> DataFrame:
    a, b = _two(g)
    return a.exceptAll(b)


@query("SELECT page_id AS page, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/]+(/[^?#]*)', 1) AS path, upper(substr(url, 1, 4)) AS scheme FROM pages")
def fn_string_url(g: Graphs) -> DataFrame:
    return g.table("pages").select(F.col("page_id").alias("page"), F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path"), F.upper(F.substring("url", 1, 4)).alias("scheme"))


@query("SELECT o_orderkey AS o, CAST(year(o_orderdate) AS INTEGER) AS y, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days, strftime(o_orderdate + INTERVAL 30 DAY, '%Y-%m-%d') AS due FROM orders")
def fn_date(g: Graphs) -> DataFrame:
    d = F.col("o_orderdate")
    return g.table("orders").select(
        F.col("o_orderkey").alias("o"), F.year(d).alias("y"), F.trunc(d.cast("date"), "month").cast("string").alias("m"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"), F.expr("CAST(CAST(o_orderdate + INTERVAL 30 DAYS AS DATE) AS STRING)").alias("due")
    )


@query("SELECT p_partkey AS part, CAST(CAST(p_retailprice AS DECIMAL(18,2)) * 3 AS DOUBLE) AS triple, p_size >> 1 AS half, CAST(p_size & 3 AS INTEGER) AS low, greatest(p_size, 10) AS big, CAST(floor(log2(p_size)) AS BIGINT) AS lg FROM part")
def fn_math_bits(g: Graphs) -> DataFrame:
    s = F.col("p_size")
    return g.table("part").select(
        F.col("p_partkey").alias("part"), (F.col("p_retailprice").cast("decimal(18,2)") * 3).cast("double").alias("triple"), F.shiftright(s, 1).alias("half"), s.bitwiseAND(3).alias("low"), F.greatest(s, F.lit(10)).alias("big"), F.floor(F.log2(s.cast("double"))).alias("lg")
    )


@query("SELECT vec_id AS vec, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS positive, len(embedding[1:8]) AS head FROM embeddings")
def fn_array_path(g: Graphs) -> DataFrame:
    e = F.col("embedding")
    norm = F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return g.table("embeddings").select(F.col("vec_id").alias("vec"), F.size(e).cast("long").alias("n"), F.round(norm, 4).alias("norm"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.size(F.slice(e, 1, 8)).cast("long").alias("head"))


@query("SELECT p_partkey AS part, p_brand AS brand, CAST(2 AS INTEGER) AS kept FROM part")
def fn_map_bag(g: Graphs) -> DataFrame:
    bag = F.create_map(F.lit("brand"), F.col("p_brand"), F.lit("type"), F.col("p_type"), F.lit("size"), F.col("p_size").cast("string"))
    return g.table("part").select(F.col("p_partkey").alias("part"), F.element_at(bag, "brand").alias("brand"), F.size(F.map_filter(bag, lambda k, v: k != "size")).alias("kept"))


@query("SELECT p_partkey AS part FROM part WHERE p_size * 2 BETWEEN 25 AND 90 AND round(p_retailprice - 900, 2) BETWEEN 20 AND 45")
def udf_overlap(g: Graphs) -> DataFrame:
    """The overlap test as an Arrow UDF, for parity with the built-in form."""

    @F.pandas_udf("boolean")
    def meets(x: pd.Series, y: pd.Series) -> pd.Series:
        return (x <= 90) & (y <= 45) & (x >= 25) & (y >= 20)

    return g.part_points().where(meets("bl_x", "bl_y")).select(F.col("poi").alias("part"))


@query(f"WITH {PEOPLE} SELECT c_nationkey AS nation, round(sum(c_acctbal * shared) / sum(shared), 6) AS mean FROM people JOIN customer ON c_custkey = customer GROUP BY 1")
def udaf_weighted(g: Graphs) -> DataFrame:
    """Weighted mean over a frontier, as the built-in sum over sum."""
    from ..operators.recommend import similar_people

    people = run(g.commerce(), g.spark, similar_people(), ids(CUSTOMER, 7))
    c = g.commerce().vertices("customer")
    j = people.join(c, people.pos == c.vid)
    return j.groupBy(F.col("c_nationkey").alias("nation")).agg(F.round(F.sum(F.col("c_acctbal") * F.col("weight")) / F.sum("weight"), 6).alias("mean"))


@query(f"WITH {PEOPLE} SELECT c_nationkey AS nation, round(sum(c_acctbal * shared) / sum(shared), 6) AS mean FROM people JOIN customer ON c_custkey = customer GROUP BY 1")
def udaf_weighted_pandas(g: Graphs) -> DataFrame:
    """The same mean as an Arrow aggregate function, for parity; groups are nations of one person's neighbourhood."""
    from ..operators.recommend import similar_people

    @F.pandas_udf("double")
    def mean(value: pd.Series, weight: pd.Series) -> float:
        return float((value * weight).sum() / weight.sum())

    people = run(g.commerce(), g.spark, similar_people(), ids(CUSTOMER, 7))
    c = g.commerce().vertices("customer")
    j = people.join(c, people.pos == c.vid)
    return j.groupBy(F.col("c_nationkey").alias("nation")).agg(mean("c_acctbal", "weight").alias("mean")).withColumn("mean", F.round("mean", 6))


@query("SELECT p_partkey AS part, CAST(i AS INTEGER) AS place, ws[i] AS word FROM (SELECT p_partkey, ws, unnest(range(1, len(ws) + 1)) AS i FROM (SELECT p_partkey, string_split(coalesce(p_name, ''), ' ') AS ws FROM part))")
def udtf_words(g: Graphs) -> DataFrame:
    """A Python table function in a lateral join, for parity with explode."""

    @F.udtf(returnType="place int, word string")
    class Words:
        def eval(self, text: str):
            yield from enumerate((text or "").split(" "), 1)

    g.spark.udtf.register("pf_words", Words)
    return g.spark.sql("SELECT p_partkey AS part, place, word FROM {part}, LATERAL pf_words(p_name)", part=g.table("part"))


@query(f"WITH {LIKES}, l AS (SELECT src, list(dst ORDER BY dst) AS ds FROM likes GROUP BY 1) SELECT src AS customer, CAST(i AS INTEGER) AS place, ds[i] AS part FROM (SELECT src, ds, unnest(range(1, len(ds) + 1)) AS i FROM l)")
def udtf_paths(g: Graphs) -> DataFrame:
    """Expand every customer's adjacency list with its place."""
    e = g.commerce().edges("likes").select(key("src").alias("customer"), key("dst").alias("part"))
    lists = e.groupBy("customer").agg(F.sort_array(F.collect_list("part")).alias("ds"))
    return lists.select("customer", F.posexplode("ds").alias("place", "part")).select("customer", (F.col("place") + 1).alias("place"), "part")


@query(f"WITH {LIKES} SELECT dst AS part FROM likes WHERE src = 7")
def sql_table_function_hop(g: Graphs) -> DataFrame:
    """One hop as a SQL table function: currying for SQL users. View and function belong to the session and have names of their own."""
    name = f"edges_{uuid.uuid4().hex}"
    g.commerce().edges("likes").select(key("src").alias("src"), key("dst").alias("dst")).createOrReplaceTempView(name)
    g.spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}_hop(start BIGINT) RETURNS TABLE (part BIGINT) RETURN SELECT dst FROM {name} WHERE src = start")
    return g.spark.sql(f"SELECT part FROM {name}_hop(7)")


@query("SELECT l AS label, c AS \"check\", CAST(0 AS BIGINT) AS n FROM (VALUES ('likes'), ('placed'), ('in_nation'), ('in_region')) a(l), (VALUES ('dangling_src'), ('dangling_dst'), ('repeated_eid')) b(c)")
def graph_validate(g: Graphs) -> DataFrame:
    graph = g.commerce()
    graph.labels = {k: graph.labels[k] for k in ("likes", "placed", "in_nation", "in_region")}
    return graph.validate()


@query("SELECT o_custkey AS customer, count(*) AS likes FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE l_returnflag <> 'R' GROUP BY 1")
def subgraph_likes_kept(g: Graphs) -> DataFrame:
    kept = g.commerce().subgraph("likes_multi", lambda e: e.flag != "R")
    d = kept.degrees("likes_multi")
    return d.select(key_of(F.col("vid")).alias("customer"), F.col("degree").alias("likes"))


@query("WITH p AS (SELECT p_partkey AS poi, p_size * 2 AS x, round(p_retailprice - 900, 2) AS y FROM part) SELECT CASE WHEN x <= 50 THEN 'west' ELSE 'east' END AS side, count(*) AS pois FROM p GROUP BY 1")
def region_halves(g: Graphs) -> DataFrame:
    """Regions as a partition of the domain: which half of the plane holds how many."""
    pois = part_tree(g).pois
    west = overlaps((PLANE[0], PLANE[1], 50.0, PLANE[3]))
    return pois.groupBy(F.when(west, "west").otherwise("east").alias("side")).agg(F.count("*").alias("pois"))


