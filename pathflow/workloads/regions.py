"""Index walks on the given tables: region trees, value trees, searches."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.regions import BOX
from ..operators import baseline, measures
from ..operators.region_tree import RegionTree, build_region_tree, many_regions, region_query, region_tests, region_trace
from ..operators.region_walks import flow, meets
from ..operators.value_tree import ValueTree
from ..plans.lower import run, touched
from ..plans.traversal import HERE
from ..sources.dictionary import dictionary
from ..sources.graph import key_of
from ..sources.scratch import stored_bytes
from .graphs import CUSTOMER, PART, Graphs
from .registry import query
from .walks import LIKES, keyed

#: The plane, the printed rectangle, a rectangle that small inputs also fill.
PLANE, RECT, SMOKE = (0.0, 0.0, 100.0, 100.0), (25.0, 20.0, 90.0, 45.0), (25.0, 2.0, 90.0, 15.0)
CAPACITY, DEPTH = 16, 12
_TREES: dict[tuple, RegionTree] = {}


def part_tree(g: Graphs) -> RegionTree:
    key = (g.spark.sparkContext.applicationId, g.sf_dir, g.state)
    if key not in _TREES:
        _TREES[key] = build_region_tree(g.part_points(), PLANE, CAPACITY, DEPTH)
    return _TREES[key]


POINTS = "pts AS (SELECT p_partkey AS poi, CAST(p_size * 2 AS DOUBLE) AS x, round(p_retailprice - 900, 2) AS y FROM part)"
HIT = f"WITH {POINTS} SELECT poi, x AS bl_x, y AS bl_y, x AS tr_x, y AS tr_y, CAST(1 AS BIGINT) AS weight FROM pts WHERE x BETWEEN 25 AND 90 AND y BETWEEN {{}} AND {{}}"


def _hits(g: Graphs, method: str, rect=RECT) -> DataFrame:
    return region_query(part_tree(g), rect, method)


@query(HIT.format(20, 45))
def region_scan(g: Graphs) -> DataFrame:
    return _hits(g, "scan")


@query(HIT.format(20, 45))
def region_plain(g: Graphs) -> DataFrame:
    return _hits(g, "plain")


@query(HIT.format(20, 45))
def region_branching(g: Graphs) -> DataFrame:
    return _hits(g, "branching")


@query(HIT.format(2, 15))
def region_prefix(g: Graphs) -> DataFrame:
    return _hits(g, "prefix", SMOKE)


#: The tree in SQL: cells on a 2^12 grid, quads by (depth, column, row); a quad exists if its parent holds more than 16.
TREE = f"""{POINTS}, grid AS (SELECT poi, x, y, least(CAST(floor(x / 100 * 4096) AS BIGINT), 4095) AS ix, least(CAST(floor(y / 100 * 4096) AS BIGINT), 4095) AS iy FROM pts),
cells AS (SELECT d, ix >> (12 - d) AS cx, iy >> (12 - d) AS cy, count(*) AS n FROM grid, range(0, 13) r(d) GROUP BY 1, 2, 3),
quads AS (SELECT c.d, c.cx, c.cy, c.n, c.cx * 100.0::DOUBLE / (1 << c.d) AS x0, c.cy * 100.0::DOUBLE / (1 << c.d) AS y0, (c.cx + 1) * 100.0::DOUBLE / (1 << c.d) AS x1, (c.cy + 1) * 100.0::DOUBLE / (1 << c.d) AS y1, c.n <= 16 OR c.d = 12 AS leaf
  FROM cells c LEFT JOIN cells p ON p.d = c.d - 1 AND p.cx = c.cx >> 1 AND p.cy = c.cy >> 1 WHERE c.d = 0 OR p.n > 16),
hung AS (SELECT g.poi, g.x, g.y, q.d, q.cx, q.cy FROM grid g JOIN quads q ON q.leaf AND q.cx = g.ix >> (12 - q.d) AND q.cy = g.iy >> (12 - q.d)),
marked AS (SELECT *, x0 <= 90 AND x1 >= 25 AND y0 <= {{1}} AND y1 >= {{0}} AS meets, x0 >= 25 AND x1 <= 90 AND y0 >= {{0}} AND y1 <= {{1}} AS fits FROM quads)"""
R = (20, 45)


@query(
    f"""WITH {TREE.format(*R)}, up AS (SELECT h.poi, h.x, h.y, count(*) AS w FROM hung h JOIN marked m ON m.fits AND m.d <= h.d AND m.cx = h.cx >> (h.d - m.d) AND m.cy = h.cy >> (h.d - m.d) GROUP BY 1, 2, 3)
SELECT h.poi, h.x AS bl_x, h.y AS bl_y, h.x AS tr_x, h.y AS tr_y, CAST(1 + coalesce(w, 0) AS BIGINT) AS weight FROM hung h LEFT JOIN up ON up.poi = h.poi WHERE h.x BETWEEN 25 AND 90 AND h.y BETWEEN {R[0]} AND {R[1]}"""
)
def region_overlay(g: Graphs) -> DataFrame:
    """The multiset of the literal flow graph: 1, and 1 more for every contained quad above."""
    return _hits(g, "overlay")


@query(
    f"""WITH {TREE.format(*R)}, q AS (SELECT d AS round, count(*) AS quads FROM marked WHERE d > 0 AND meets GROUP BY 1),
p AS (SELECT d + 1 AS round, count(*) AS pois FROM hung WHERE x BETWEEN 25 AND 90 AND y BETWEEN {R[0]} AND {R[1]} GROUP BY 1)
SELECT CAST(round AS INTEGER) AS round, coalesce(quads, 0) AS quads, coalesce(pois, 0) AS pois FROM q FULL JOIN p USING (round)""",
    name="region_trace",
)
def region_trace_rounds(g: Graphs) -> DataFrame:
    return region_trace(part_tree(g), RECT)


@query(
    f"""WITH {TREE.format(*R)}, a AS (SELECT * FROM marked WHERE meets OR d = 0),
load AS (SELECT q.d, q.cx, q.cy, (SELECT count(*) FROM quads c WHERE c.d = q.d + 1 AND c.cx >> 1 = q.cx AND c.cy >> 1 = q.cy) + (SELECT count(*) FROM hung h WHERE h.d = q.d AND h.cx = q.cx AND h.cy = q.cy) AS tests FROM quads q),
la AS (SELECT a.*, load.tests FROM a JOIN load USING (d, cx, cy)), hits AS (SELECT count(*) AS n FROM pts WHERE x BETWEEN 25 AND 90 AND y BETWEEN {R[0]} AND {R[1]}),
arm AS (SELECT * FROM la WHERE NOT EXISTS (SELECT 1 FROM marked m WHERE m.fits AND m.d = la.d - 1 AND m.cx = la.cx >> 1 AND m.cy = la.cy >> 1))
SELECT 'scan' AS method, (SELECT count(*) FROM pts) AS region_tests, CAST(0 AS BIGINT) AS containment_tests, n AS results FROM hits
UNION ALL SELECT 'plain', (SELECT CAST(sum(tests) AS BIGINT) FROM la), 0, n FROM hits
UNION ALL SELECT 'branching', (SELECT CAST(coalesce(sum(tests), 0) AS BIGINT) FROM la WHERE NOT fits), (SELECT count(*) FROM arm), n FROM hits
UNION ALL SELECT 'overlay', (SELECT CAST(sum(tests) AS BIGINT) FROM la), (SELECT count(*) FROM la), n FROM hits"""
)
def region_tests_saved(g: Graphs) -> DataFrame:
    return region_tests(part_tree(g), RECT)


@query(f"WITH {TREE.format(*R)} SELECT count(*) AS quads, count(*) FILTER (WHERE leaf) AS leaves, CAST(max(d) AS INTEGER) AS depth, max(n) FILTER (WHERE leaf) AS largest_leaf, (SELECT count(*) FROM pts) AS pois FROM quads")
def region_tree_profile(g: Graphs) -> DataFrame:
    t = part_tree(g)
    q = t.quads.agg(F.count("*").alias("quads"), F.count_if("leaf").alias("leaves"), F.max("depth").cast("int").alias("depth"), F.max(F.when(F.col("leaf"), F.col("n"))).alias("largest_leaf"))
    return q.crossJoin(F.broadcast(t.pois.agg(F.count("*").alias("pois"))))


BOXES = "boxes AS (SELECT l_orderkey AS poi, epoch(min(l_shipdate)) AS bl_x, min(l_extendedprice) AS bl_y, epoch(max(l_shipdate)) AS tr_x, max(l_extendedprice) AS tr_y FROM lineitem GROUP BY 1)"
BOX_RECT = (852076800.0, 20000.0, 930700800.0, 40000.0)


def _box_hits(g: Graphs, assign: str) -> DataFrame:
    boxes = g.order_boxes()
    e = boxes.agg(*[F.min(c) for c in BOX[:2]], *[F.max(c) for c in BOX[2:]]).first()
    tree = build_region_tree(boxes, tuple(e), 64, 10, assign)
    return region_query(tree, BOX_RECT, "branching").select("poi", *BOX).distinct()


BOX_SQL = f"WITH {BOXES} SELECT * FROM boxes WHERE bl_x <= {BOX_RECT[2]} AND tr_x >= {BOX_RECT[0]} AND bl_y <= {BOX_RECT[3]} AND tr_y >= {BOX_RECT[1]}"


@query(BOX_SQL)
def region_boxes(g: Graphs) -> DataFrame:
    return _box_hits(g, "enclosing")


@query(BOX_SQL)
def region_boxes_every(g: Graphs) -> DataFrame:
    """Boxes under every leaf that they touch, then one row per box."""
    return _box_hits(g, "every")


@query(f"WITH {POINTS}, r AS (SELECT i AS rect, i * 4.0 AS x0, i * 3.0 AS y0, i * 4.0 + 20 AS x1, i * 3.0 + 25 AS y1 FROM range(0, 20) t(i)) SELECT rect, count(*) AS pois FROM r JOIN pts ON x BETWEEN x0 AND x1 AND y BETWEEN y0 AND y1 GROUP BY 1")
def region_many_rects(g: Graphs) -> DataFrame:
    i = F.col("id")
    rects = g.spark.range(20).select(i.alias("rect"), (i * 4.0).alias("x0"), (i * 3.0).alias("y0"), (i * 4.0 + 20).alias("x1"), (i * 3.0 + 25).alias("y1"))
    return many_regions(part_tree(g), rects)


@query(f"WITH {POINTS}, {LIKES} SELECT src AS customer, count(*) AS times FROM pts JOIN likes ON dst = poi WHERE x BETWEEN 25 AND 90 AND y BETWEEN 2 AND 15 GROUP BY 1")
def region_then_likers(g: Graphs) -> DataFrame:
    """Index walk and domain walk as one plan."""
    hits = _hits(g, "branching", SMOKE).select((F.col("poi") + (PART << 56)).alias("pos"))
    return keyed(run(g.commerce(), g.spark, HERE.into("likes"), frame=hits), "customer")


@query("SELECT vec_id AS vec, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y FROM embeddings WHERE embedding[1] BETWEEN -0.1 AND 0.1 AND embedding[2] BETWEEN -0.05 AND 0.2")
def embedding_region(g: Graphs) -> DataFrame:
    tree = build_region_tree(g.embedding_points(), (-1.0, -1.0, 1.0, 1.0), 32, 10)
    return region_query(tree, (-0.1, -0.05, 0.1, 0.2)).select(F.col("poi").alias("vec"), F.col("bl_x").alias("x"), F.col("bl_y").alias("y"))


@query("SELECT s_suppkey AS supplier FROM supplier WHERE s_nationkey BETWEEN 3 AND 12 AND s_acctbal BETWEEN 1000 AND 6000")
def supplier_region(g: Graphs) -> DataFrame:
    tree = build_region_tree(g.supplier_points(), (0.0, -1000.0, 25.0, 10000.0), 16, 10)
    return region_query(tree, (3, 1000, 12, 6000), "plain").select(F.col("poi").alias("supplier"))


@query(HIT.format(20, 45).replace(", CAST(1 AS BIGINT) AS weight", "").replace("poi, x AS bl_x, y AS bl_y, x AS tr_x, y AS tr_y", "poi"))
def region_walk_in_graph(g: Graphs) -> DataFrame:
    """The plain descent written as a walk of the step algebra: hop along the sub edges whose child overlaps, until nothing is left."""
    body = HERE.out_edges("sub") >> meets(RECT).head()
    out = run(part_tree(g).as_graph(), g.spark, HERE.repeat(body, emit="all").keep("type", "=", "poi"), [(20 << 56) + 1])
    return keyed(out, "poi", None)


@query(
    f"""WITH {TREE.format(*R)}, up AS (SELECT h.poi, count(*) AS w FROM hung h JOIN marked m ON m.fits AND m.d <= h.d AND m.cx = h.cx >> (h.d - m.d) AND m.cy = h.cy >> (h.d - m.d) GROUP BY 1)
SELECT h.poi, CAST(1 + coalesce(w, 0) AS BIGINT) AS weight FROM hung h LEFT JOIN up ON up.poi = h.poi WHERE h.x BETWEEN 25 AND 90 AND h.y BETWEEN {R[0]} AND {R[1]}"""
)
def region_flow_walk(g: Graphs) -> DataFrame:
    """The literal flow graph, composed of its five functions in the step algebra."""
    return keyed(run(part_tree(g).as_graph(), g.spark, flow(RECT), [(20 << 56) + 1]), "poi", "weight")


# -- value trees and searches


def _names(g: Graphs) -> ValueTree:
    key = (g.spark.sparkContext.applicationId, g.sf_dir, g.state, "names")
    if key not in _TREES:
        _TREES[key] = ValueTree(g.table("customer").select(F.col("c_custkey").alias("key"), F.col("c_name").alias("value")), CUSTOMER, 16)
    return _TREES[key]


@query("SELECT c_custkey AS customer FROM customer WHERE c_name = 'Customer#000000042'")
def name_tree_lookup(g: Graphs) -> DataFrame:
    return keyed(_names(g).lookup(g.spark, "Customer#000000042"), "customer", None)


@query("SELECT c_custkey AS customer FROM customer WHERE c_name BETWEEN 'Customer#000000042' AND 'Customer#000000099'")
def name_tree_range(g: Graphs) -> DataFrame:
    return keyed(_names(g).range(g.spark, "Customer#000000042", "Customer#000000099"), "customer", None)


@query("SELECT c_custkey AS customer FROM customer WHERE c_name = 'Customer#000000042'")
def sorted_lookup(g: Graphs) -> DataFrame:
    """The external index: a copy sorted by value, whose row groups are skipped by their least and greatest value."""
    rows = g._stored("sorted_names", lambda: g.table("customer").select("c_name", "c_custkey"), "c_name")
    return rows.where(F.col("c_name") == "Customer#000000042").select(F.col("c_custkey").alias("customer"))


@query("SELECT doc_id AS doc FROM documents WHERE list_contains(regexp_extract_all(lower(text), '\\p{L}+'), 'stingha')")
def text_lookup(g: Graphs) -> DataFrame:
    """Inverted table: word -> documents, sorted by word."""
    index = g._stored("inverted", g.words, "word")
    return index.where(F.col("word") == "stingha").select("doc")


@query("SELECT l_partkey AS part, count(*) AS times FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_shipdate < TIMESTAMP '1997-02-01' GROUP BY 1")
def edge_property_lookup(g: Graphs) -> DataFrame:
    """Edges found by their own property, then their heads."""
    e = g.commerce().edges("contains").where("p_l_shipdate >= timestamp_ntz '1997-01-01' AND p_l_shipdate < timestamp_ntz '1997-02-01'")
    return e.groupBy(key_of(F.col("dst")).alias("part")).agg(F.count("*").alias("times"))


def _guessed(g: Graphs) -> tuple[DataFrame, int, int]:
    """The keys of all parts, and the range that the guesser is told: from the least key to the greatest."""
    keys = g.table("part").select(F.col("p_partkey").alias("target")).where("target IS NOT NULL").distinct()
    low, high = keys.agg(F.min("target"), F.max("target")).first()
    return keys, low or 0, high or 0


@query(
    """WITH RECURSIVE k AS (SELECT DISTINCT p_partkey AS target FROM part WHERE p_partkey IS NOT NULL), g AS (SELECT target, (SELECT min(target) FROM k) AS lo, (SELECT max(target) FROM k) AS hi, 0 AS guesses, false AS done FROM k
UNION ALL SELECT target, CASE WHEN (lo + hi) // 2 < target THEN (lo + hi) // 2 + 1 ELSE lo END, CASE WHEN (lo + hi) // 2 > target THEN (lo + hi) // 2 - 1 ELSE hi END, guesses + 1, (lo + hi) // 2 = target FROM g WHERE NOT done)
SELECT target, guesses FROM g WHERE done"""
)
def guess_number(g: Graphs) -> DataFrame:
    """Every part's key is a number to guess between the least and the greatest key."""
    keys, low, high = _guessed(g)
    # a round is a level of the recursion, which holds the rows of all rounds
    g.spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")
    return baseline.guess_numbers(g.spark, low, high, keys)


@query("SELECT DISTINCT p_partkey AS target, CAST(p_partkey - (SELECT min(p_partkey) FROM part) + 1 AS INTEGER) AS guesses FROM part WHERE p_partkey IS NOT NULL")
def guess_number_linear(g: Graphs) -> DataFrame:
    keys, low, high = _guessed(g)
    return baseline.guess_numbers_linear(g.spark, low, high, keys)


@query("SELECT count(*) AS rows_read, count(*) FILTER (WHERE c_name = 'Customer#000000042') AS found FROM customer")
def scan_lookup(g: Graphs) -> DataFrame:
    return baseline.scan_lookup(g.table("customer"), "c_name", "Customer#000000042")


@query("SELECT CAST(ceil(log(count(*)) / log(16)) AS INTEGER) AS levels, CAST(1 AS BIGINT) AS found, count(*) > 0 AND (SELECT count(*) = 1 FROM customer WHERE c_name = 'Customer#000000042') AS bounded FROM customer")
def index_probe_compare(g: Graphs) -> DataFrame:
    """In-graph levels beside the halving probes of a sorted copy: both logarithmic (probes within log2(n + 1))."""
    tree = _names(g)
    ranks = dictionary(g.table("customer").select(F.col("c_name").alias("value")), "value")
    hit = baseline.bisect_lookup(g.spark, ranks, "value", "Customer#000000042")
    n = g.table("customer").agg(F.count("*").alias("n"))
    return hit.crossJoin(n).agg(F.lit(tree.levels).alias("levels"), F.count("*").alias("found"), F.max(F.col("guesses") <= F.ceil(F.log2(F.col("n") + 1))).alias("bounded"))


PROBES = """WITH RECURSIVE names AS (SELECT DISTINCT c_name FROM customer), r AS (SELECT c_name, row_number() OVER (ORDER BY c_name) - 1 AS k FROM names), n AS (SELECT count(*) AS n FROM names),
t AS (SELECT k, n, CAST(ceil(log(n) / log(16)) AS INTEGER) AS levels FROM r, n WHERE c_name = 'Customer#000000042'),
g AS (SELECT k, CAST(0 AS BIGINT) AS lo, n - 1 AS hi, 0 AS probes, false AS done FROM t
UNION ALL SELECT k, CASE WHEN (lo + hi) // 2 < k THEN (lo + hi) // 2 + 1 ELSE lo END, CASE WHEN (lo + hi) // 2 > k THEN (lo + hi) // 2 - 1 ELSE hi END, probes + 1, (lo + hi) // 2 = k FROM g WHERE NOT done)
SELECT 'in_graph' AS lookup, CAST(sum(least(16, CAST(ceil(n / pow(16, l)) AS BIGINT) - 16 * (k // CAST(pow(16, l + 1) AS BIGINT)))) AS BIGINT) AS probes FROM t, range(0, 20) x(l) WHERE l < levels
UNION ALL SELECT 'external', max(probes) FROM g UNION ALL SELECT 'scan', count(*) FROM customer"""


@query(PROBES)
def index_probes(g: Graphs) -> DataFrame:
    """Entries that one lookup reads: children tested on the way down the tree in the graph, halving probes of a sorted copy, rows of a scan."""
    tree, name = _names(g), "Customer#000000042"
    walk = HERE
    for _ in range(tree.levels):
        walk = walk >> tree.descent(name, name)
    tested = touched(tree.as_graph(), g.spark, walk, [tree.root]).agg(F.sum("edges").alias("probes"))
    ranks = dictionary(g.table("customer").select(F.col("c_name").alias("value")), "value")
    halving = baseline.bisect_lookup(g.spark, ranks, "value", name).select(F.col("guesses").cast("long").alias("probes"))
    scan = g.table("customer").agg(F.count("*").alias("probes"))
    out = tested.select(F.lit("in_graph").alias("lookup"), "probes")
    for label, one in (("external", halving), ("scan", scan)):
        out = out.unionByName(one.select(F.lit(label).alias("lookup"), "probes"))
    return out


@query(f"WITH {TREE.format(*R)} SELECT (SELECT count(*) FROM pts) AS rows, (SELECT count(*) FROM quads) AS nodes")
def index_space(g: Graphs) -> DataFrame:
    t = part_tree(g)
    return measures.index_space(t.pois, t.quads)


@query(None)
def index_bytes(g: Graphs) -> DataFrame:
    """Bytes on disk of the indexed rows and of each index structure."""
    tree, names = part_tree(g), _names(g)
    rows = [("part", g.table("part")), ("region_quads", tree.quads), ("region_pois", tree.pois), ("customer", g.table("customer")), ("name_nodes", names.nodes), ("name_ranks", names.ranks)]
    return g.spark.createDataFrame([(name, stored_bytes(df)) for name, df in rows], "structure string, bytes long")
