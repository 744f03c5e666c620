"""Plane partition by density, stored as part of the graph; region queries as walks over it.

Build, without a driver loop: points fall into the finest cells (interleaved bits); counts per cell roll up to all depths; a cell exists if its
parent holds more than `capacity`. What is exploded are cell counts, not points. Quad key: 1 << 2d | prefix.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.regions import BOX, cell_index, cell_path, checked, inside, overlaps, touched_cells
from ..sources.graph import EdgeLabel, PropertyGraph, VertexClass, vid
from ..sources.scratch import stored

QUAD, POI = 20, 21
#: Topmost contained quads up to this many become range predicates on the scan; more are joined.
RANGES = 500


@dataclass
class RegionTree:
    """quads: quad, parent, depth, n, leaf, box. pois: poi, quad (where it hangs), at (path where that quad begins), depth, box. spread: a POI may hang
    in several places."""

    quads: DataFrame
    pois: DataFrame
    max_depth: int
    spread: bool = False

    @cached_property
    def sub(self) -> DataFrame:
        """Edges from parent to child, clustered by parent. They carry the child's corners and type, so that a round of a walk meets this table alone."""
        down = self.quads.where("parent IS NOT NULL").select(vid(QUAD, F.col("parent")).alias("src"), vid(QUAD, F.col("quad")).alias("dst"), *BOX, F.lit("quad").alias("type"))
        leaf = self.pois.select(vid(QUAD, F.col("quad")).alias("src"), vid(POI, F.col("poi")).alias("dst"), *BOX, F.lit("poi").alias("type"))
        edges = down.unionByName(leaf).withColumn("eid", F.col("dst"))
        return stored(edges.repartitionByRange("src").sortWithinPartitions("src"), "sub")

    def as_graph(self) -> PropertyGraph:
        """Vertices of class quad and poi with their corners and type; edges `sub` from parent to child, with those of the child."""
        corners = (*BOX, "type")
        quads = VertexClass("quad", QUAD, lambda: self.quads.select(vid(QUAD, F.col("quad")).alias("vid"), *BOX, F.lit("quad").alias("type")), corners)
        pois = VertexClass("poi", POI, lambda: self.pois.select(vid(POI, F.col("poi")).alias("vid"), *BOX, F.lit("poi").alias("type")), corners)

        return PropertyGraph.of([quads, pois], [EdgeLabel("sub", lambda: self.sub, corners, tree=True)])


def build_region_tree(boxes: DataFrame, root: tuple[float, float, float, float], capacity: int = 16, max_depth: int = 12, assign: str = "enclosing") -> RegionTree:
    """boxes: poi, bl_x, bl_y, tr_x, tr_y (points have equal corners). Rows with a null corner are not indexed.

    Density is that of box centres. assign: 'enclosing' hangs a box under the smallest quad that holds it; 'every' under every
    leaf that it touches (results then need a dedup by poi), see `_under_every_leaf`. Coincident points may overfill a leaf at max_depth.
    """
    x0, y0, x1, y1 = checked(root)
    if capacity < 1 or not 0 <= max_depth <= 27:
        raise ValueError(f"capacity {capacity}, max_depth {max_depth}")
    top = max_depth
    whole = boxes.where(" AND ".join(f"{c} IS NOT NULL" for c in BOX)).select("poi", *BOX)

    def index(x, y):
        return cell_index(x, x0, x1, top), cell_index(y, y0, y1, top)

    ix, iy = index((F.col("bl_x") + F.col("tr_x")) / 2, (F.col("bl_y") + F.col("tr_y")) / 2)
    low, high = cell_path(*index(F.col("bl_x"), F.col("bl_y"))), cell_path(*index(F.col("tr_x"), F.col("tr_y")))
    differ = low.bitwiseXOR(high)
    common = F.when(differ == 0, F.lit(top)).otherwise(F.lit(top) - F.ceil(F.length(F.bin(differ)) / 2).cast("int"))
    placed = whole.select("poi", *BOX, ix.alias("ix"), iy.alias("iy"), low.alias("path"), common.alias("common"))
    cells = placed.groupBy(cell_path(F.col("ix"), F.col("iy")).alias("cell"), "ix", "iy").agg(F.count("*").alias("n"))
    every = cells.select("cell", "ix", "iy", "n", F.explode(F.sequence(F.lit(0), F.lit(top))).alias("depth"))
    up = F.expr(f"shiftright(cell, 2 * ({top} - depth))")
    counts = every.groupBy(F.expr("shiftleft(1L, 2 * depth)").bitwiseOR(up).alias("quad"), "depth").agg(F.sum("n").alias("n"), F.min("ix").alias("ix"), F.min("iy").alias("iy"))
    counts = stored(counts, "cells")
    dense = counts.where(F.col("n") > capacity).select(F.col("quad").alias("_p"))
    side = F.pow(F.lit(2.0), F.col("depth"))
    qx, qy = (F.expr(f"shiftright({c}, {top} - depth)") for c in ("ix", "iy"))
    quads = counts.join(dense, F.shiftright("quad", 2) == F.col("_p"), "left").where("depth = 0 OR _p IS NOT NULL").select(
        "quad",
        F.when(F.col("depth") > 0, F.shiftright("quad", 2)).alias("parent"),
        "depth",
        "n",
        ((F.col("n") <= capacity) | (F.col("depth") == top)).alias("leaf"),
        (F.lit(x0) + qx * (x1 - x0) / side).alias("bl_x"),
        (F.lit(y0) + qy * (y1 - y0) / side).alias("bl_y"),
        (F.lit(x0) + (qx + 1) * (x1 - x0) / side).alias("tr_x"),
        (F.lit(y0) + (qy + 1) * (y1 - y0) / side).alias("tr_y"),
    )
    quads = stored(quads, "quads")
    begin = F.expr(f"shiftleft(quad, 2 * ({top} - depth))").bitwiseAND(F.lit((1 << (2 * top)) - 1))
    if assign == "enclosing":
        # the deepest existing quad on the path, not below the common depth; resolved once per distinct cell
        slots = placed.select("path", "common").distinct().select("path", "common", F.explode(F.sequence(F.lit(0), F.col("common"))).alias("d"))
        key = F.expr("shiftleft(1L, 2 * d)").bitwiseOR(F.expr(f"shiftright(path, 2 * ({top} - d))"))
        found = slots.withColumn("quad", key).join(quads.select("quad"), "quad").groupBy("path", "common").agg(F.max("quad").alias("quad"))
        hung = placed.join(found, ["path", "common"]).join(quads.select("quad", "depth"), "quad")
    elif assign == "every":
        quads = stored(quads.unionByName(_empty_quarters(quads, (x0, y0, x1, y1))), "quads")
        return RegionTree(quads, _under_every_leaf(whole, quads, (x0, y0, x1, y1), top), top, True)
    else:
        raise ValueError(assign)
    pois = hung.select("poi", "quad", begin.alias("at"), "depth", *BOX)
    return RegionTree(quads, stored(pois.repartitionByRange("at").sortWithinPartitions("at"), "pois"), top)


def _empty_quarters(quads: DataFrame, root) -> DataFrame:
    """Quarters of inner quads that hold no box centre, as leaves: a box may reach into them all the same."""
    x0, y0, x1, y1 = root
    side = F.pow(F.lit(2.0), F.col("depth"))
    # the place of a quad in its row and column of the grid, from its corner: it is a whole number up to rounding
    place = [F.round((F.col(c) - low) / (high - low) * side / 2).cast("long") if high > low else F.lit(0).cast("long") for c, low, high in (("bl_x", x0, x1), ("bl_y", y0, y1))]
    inner = quads.where("NOT leaf").select(F.col("quad").alias("parent"), (F.col("depth") + 1).alias("depth"), "bl_x", "bl_y")
    four = inner.select("parent", "depth", place[0].alias("px"), place[1].alias("py"), F.explode(F.array(*map(F.lit, range(4)))).alias("q"))
    kx, ky = F.col("px") * 2 + F.col("q") % 2, F.col("py") * 2 + F.shiftright("q", 1)
    four = four.select(F.shiftleft("parent", 2).bitwiseOR(F.col("q").cast("long")).alias("quad"), "parent", "depth", kx.alias("kx"), ky.alias("ky"))
    return four.join(quads.select("quad"), "quad", "left_anti").select(
        "quad",
        "parent",
        "depth",
        F.lit(0).cast("long").alias("n"),
        F.lit(True).alias("leaf"),
        (F.lit(x0) + F.col("kx") * (x1 - x0) / side).alias("bl_x"),
        (F.lit(y0) + F.col("ky") * (y1 - y0) / side).alias("bl_y"),
        (F.lit(x0) + (F.col("kx") + 1) * (x1 - x0) / side).alias("tr_x"),
        (F.lit(y0) + (F.col("ky") + 1) * (y1 - y0) / side).alias("tr_y"),
    )


def _under_every_leaf(boxes: DataFrame, quads: DataFrame, root, top: int) -> DataFrame:
    """POI rows of boxes under every leaf that they touch, without a row for each.

    Only quads with a corner of the box in them are followed down to their leaves. Any other quad that the box touches it crosses whole along an axis; the box
    hangs there, and stands for the leaves below that its corners meet. So each touched leaf is under one row of the box (`touched_leaves` lists them), and a box
    has 12 rows a depth at most. What is stored is one row per box and corner; the others are counted up from it by each reader.
    """
    x0, y0, x1, y1 = root
    (i0, i1), (j0, j1) = touched_cells(F.col("bl_x"), F.col("tr_x"), x0, x1, top), touched_cells(F.col("bl_y"), F.col("tr_y"), y0, y1, top)
    span = boxes.where(overlaps(root)).select("poi", *BOX, i0.alias("i0"), i1.alias("i1"), j0.alias("j0"), j1.alias("j1"))
    span = span.select("*", *[cell_path(F.col(f"i{k & 1}"), F.col(f"j{k >> 1}")).alias(f"p{k}") for k in range(4)])
    paths = span.select(F.explode(F.array("p0", "p1", "p2", "p3")).alias("path")).distinct()
    slots = paths.select("path", F.explode(F.sequence(F.lit(0), F.lit(top))).alias("d"))
    leaves = slots.join(quads.where("leaf").select("quad"), F.expr(f"shiftleft(1L, 2 * d) | shiftright(path, 2 * ({top} - d))") == F.col("quad")).select("path", F.col("d").alias("leaf_depth"))
    corner = span.select("*", F.posexplode(F.array("p0", "p1", "p2", "p3")).alias("k", "path")).where("(k < 1 OR p0 <> path) AND (k < 2 OR p1 <> path) AND (k < 3 OR p2 <> path)")
    corner = stored(corner.join(stored(leaves, "leaves"), "path"), "corners")

    up = f"2 * ({top} - d)"
    # a quad above several corners is taken from the first of them
    mine = " AND ".join(f"(k < {k + 1} OR shiftright(p{k}, {up}) <> shiftright(path, {up}))" for k in range(3))
    down = corner.select("*", F.explode(F.sequence(F.lit(0), F.col("leaf_depth"))).alias("d")).where(mine)
    down = down.select("*", F.explode(F.when(F.col("d") < F.col("leaf_depth"), F.array(*map(F.lit, range(4)))).otherwise(F.array(F.lit(-1)))).alias("q"))
    at_leaf = f"shiftleft(1L, 2 * d) | shiftright(path, {up})"
    quad = F.expr(f"CASE WHEN q < 0 THEN {at_leaf} ELSE shiftleft({at_leaf}, 2) | q END")
    kx, ky = F.expr(f"shiftright(IF(k % 2 = 0, i0, i1), {top} - d) * 2 + q % 2"), F.expr(f"shiftright(IF(k < 2, j0, j1), {top} - d) * 2 + shiftright(q, 1)")
    down = down.select("poi", *BOX, "d", "q", "i0", "i1", "j0", "j1", "p0", "p1", "p2", "p3", quad.alias("quad"), kx.alias("kx"), ky.alias("ky"))
    low = f"({top} - d - 1)"
    crossed = f"kx BETWEEN shiftright(i0, {low}) AND shiftright(i1, {low}) AND ky BETWEEN shiftright(j0, {low}) AND shiftright(j1, {low})"
    no_corner = " AND ".join(f"quad <> (shiftleft(1L, 2 * d + 2) | shiftright(p{k}, 2 * {low}))" for k in range(4))
    depth = F.expr("IF(q < 0, d, d + 1)")
    begin = F.expr(f"shiftleft(quad, 2 * ({top} - IF(q < 0, d, d + 1)))").bitwiseAND(F.lit((1 << (2 * top)) - 1))
    return down.where(f"q < 0 OR ({crossed} AND {no_corner})").select("poi", "quad", begin.alias("at"), depth.alias("depth"), *BOX)


def touched_leaves(tree: RegionTree) -> DataFrame:
    """(poi, quad): every leaf that each box of an 'every' tree touches, once."""
    leaves = tree.quads.where("leaf").select(F.col("quad").alias("leaf_quad"), "depth", *[F.col(c).alias(f"q_{c}") for c in BOX])
    above = leaves.select("*", F.explode(F.sequence(F.lit(0), F.col("depth"))).alias("u")).withColumn("quad", F.expr("shiftright(leaf_quad, 2 * u)")).drop("depth", "u")
    met = tree.pois.select("poi", "quad", *BOX).join(above, "quad").where(overlaps([F.col(c) for c in BOX], "q_"))
    return met.select("poi", F.col("leaf_quad").alias("quad"))


def tree_of(quads: DataFrame, sub: DataFrame, pois: DataFrame) -> RegionTree:
    """A hand-made tree: quads (quad, box), sub (parent, quad), pois (poi, quad, box). It has no paths, so no `prefix` method."""
    return RegionTree(quads.join(sub, "quad", "left").select("quad", "parent", *BOX), pois.select("poi", "quad", *BOX), -1)


def _descend(tree: RegionTree, rect, columns: str, start: str, step: str, where: str) -> DataFrame:
    """A recursive walk over quads as one query; the plan has one join per round and no driver loop of ours."""
    spark = tree.quads.sparkSession
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")
    x0, y0, x1, y1 = rect
    fits = f"(c.bl_x >= {x0!r}D AND c.bl_y >= {y0!r}D AND c.tr_x <= {x1!r}D AND c.tr_y <= {y1!r}D)"
    meets = f"(c.bl_x <= {x1!r}D AND c.bl_y <= {y1!r}D AND c.tr_x >= {x0!r}D AND c.tr_y >= {y0!r}D)"
    fill = lambda s: s.replace("FITS", fits).replace("MEETS", meets)
    return spark.sql(
        f"WITH RECURSIVE walk({columns}) AS (SELECT {fill(start)} FROM {{quads}} c WHERE c.parent IS NULL "
        f"UNION ALL SELECT {fill(step)} FROM walk w JOIN {{quads}} c ON c.parent = w.quad WHERE {fill(where)}) SELECT * FROM walk",
        quads=tree.quads,
    )


def open_quads(tree: RegionTree, rect) -> DataFrame:
    """A of the flow graph: quad, round, contained. The root is in, untested."""
    return _descend(tree, checked(rect), "quad, round, contained", "c.quad, 0, FITS", "c.quad, w.round + 1, FITS", "MEETS")


def branch_quads(tree: RegionTree, rect) -> DataFrame:
    """quad, round, contained: a contained quad's subtree is walked without tests and inherits the flag."""
    return _descend(tree, checked(rect), "quad, round, contained", "c.quad, 0, FITS", "c.quad, w.round + 1, w.contained OR FITS", "w.contained OR MEETS")


def contained_quads(tree: RegionTree, rect) -> DataFrame:
    """B of the flow graph: (quad, weight): how often the free descent reaches a quad from contained members of A."""
    spark = tree.quads.sparkSession
    seeds = stored(open_quads(tree, rect).where("contained").select("quad"), "seeds")
    walk = spark.sql("WITH RECURSIVE b(quad) AS (SELECT quad FROM {seeds} UNION ALL SELECT c.quad FROM b JOIN {quads} c ON c.parent = b.quad) SELECT * FROM b", seeds=seeds, quads=tree.quads)
    return walk.groupBy("quad").agg(F.count("*").alias("weight"))


def region_query(tree: RegionTree, rect, method: str = "branching") -> DataFrame:
    """POIs that meet the rectangle: poi, box, weight.

    scan: test all. plain: descend by overlapping children, test every POI met. branching: contained branches are not tested. prefix: contained
    quads become ranges of the POI order. overlay: the literal flow graph, a multiset (a POI under a quad d levels below the topmost contained one weighs d + 2).
    """
    rect = checked(rect)
    one = F.lit(1).cast("long").alias("weight")
    pois = tree.pois
    if method == "scan":
        return pois.where(overlaps(rect)).select("poi", *BOX, one)
    # many rows meet few quads there: a stored walk has a size, by which Spark may broadcast it instead of shuffling them
    kept = (lambda walk: stored(walk, "walk")) if tree.spread else (lambda walk: walk)
    if method == "plain":
        return pois.join(kept(open_quads(tree, rect).select("quad")), "quad").where(overlaps(rect)).select("poi", *BOX, one)
    if method == "branching":
        return pois.join(kept(branch_quads(tree, rect).select("quad", "contained")), "quad").where(F.col("contained") | overlaps(rect)).select("poi", *BOX, one)
    if method == "overlay":
        tested = pois.join(open_quads(tree, rect).select("quad"), "quad").where(overlaps(rect)).select("poi", *BOX, one)
        free = pois.join(contained_quads(tree, rect), "quad").select("poi", *BOX, "weight")
        return tested.unionByName(free).groupBy("poi", *BOX).agg(F.sum("weight").alias("weight"))
    if method == "prefix":
        if tree.max_depth < 0:
            raise ValueError("a hand-made tree has no paths")
        return _by_ranges(tree, rect).select("poi", *BOX, one)
    raise ValueError(method)


def _by_ranges(tree: RegionTree, rect) -> DataFrame:
    # the open arm stops at contained quads, so those it meets are topmost; the driver gets RANGES + 1 rows of each kind at most
    walk = _descend(tree, rect, "quad, depth, contained", "c.quad, c.depth, FITS", "c.quad, c.depth, FITS", "NOT w.contained AND MEETS")
    got = walk.limit(2 * RANGES + 1).collect()
    if len(got) <= 2 * RANGES:
        hit = F.lit(False)
        for lo, hi, d in _merged_ranges([r for r in got if r["contained"]], tree.max_depth):
            hit = hit | (F.col("at").between(lo, hi) & (F.col("depth") >= d))
        # what hangs under an open quad is tested in the same pass
        border = [r["quad"] for r in got if not r["contained"]]
        return tree.pois.where(hit | (F.col("quad").isin(border) & overlaps(rect))).select("poi", *BOX)
    walk = stored(walk, "arm")
    tested = tree.pois.join(walk.where("NOT contained").select("quad"), "quad").where(overlaps(rect)).select("poi", *BOX)
    tops = walk.where("contained").select(F.col("depth").alias("d"), F.expr(f"shiftleft(quad, 2 * ({tree.max_depth} - depth))").bitwiseAND(F.lit((1 << (2 * tree.max_depth)) - 1)).alias("lo"))
    free = None
    for d in range(tree.max_depth + 1):  # equi-joins, one per depth: a quad at depth d is a prefix of what hangs below
        shift = 2 * (tree.max_depth - d)
        one = tree.pois.where(F.col("depth") >= d).join(tops.where(F.col("d") == d).select(F.shiftright("lo", shift).alias("_p")), F.shiftright("at", shift) == F.col("_p"), "left_semi").select("poi", *BOX)
        free = one if free is None else free.unionByName(one)
    return tested.unionByName(free)


def _merged_ranges(quads: list, top: int) -> list[tuple[int, int, int]]:
    """(lo, hi, depth) of the quads' stretches of the cell order; neighbours of one depth become one."""
    out: list[tuple[int, int, int]] = []
    for d, lo in sorted((r["depth"], (r["quad"] << 2 * (top - r["depth"])) & ((1 << 2 * top) - 1)) for r in quads):
        hi = lo + (1 << 2 * (top - d)) - 1
        if out and out[-1][2] == d and out[-1][1] + 1 == lo:
            out[-1] = (out[-1][0], hi, d)
        else:
            out.append((lo, hi, d))
    return out


def region_tests(tree: RegionTree, rect) -> DataFrame:
    """(method, region_tests, containment_tests, results) of scan, plain, branching and overlay."""
    rect = checked(rect)
    a = stored(open_quads(tree, rect), "open")
    b = stored(branch_quads(tree, rect), "branches")
    # quads whose children are tested: all of A in the plain and overlay walk; A without its contained members in the branching walk
    child = tree.quads.where("parent IS NOT NULL").groupBy(F.col("parent").alias("quad")).agg(F.count("*").alias("quads"))
    hang = tree.pois.groupBy("quad").agg(F.count("*").alias("pois"))
    load = tree.quads.select("quad").join(child, "quad", "left").join(hang, "quad", "left").select("quad", (F.coalesce("quads", F.lit(0)) + F.coalesce("pois", F.lit(0))).alias("tests"))

    def tests(quads: DataFrame) -> DataFrame:
        return quads.join(load, "quad").agg(F.coalesce(F.sum("tests"), F.lit(0)).cast("long").alias("region_tests"))

    tested = b.join(tree.quads.select("quad", "parent"), "quad").join(b.where("contained").select(F.col("quad").alias("_c")), F.col("parent") == F.col("_c"), "left_anti")
    count = lambda df, name: df.agg(F.count("*").alias(name))
    hits = count(region_query(tree, rect, "scan"), "results")
    rows = [
        ("scan", count(tree.pois.select("poi"), "region_tests"), tree.pois.limit(0)),
        ("plain", tests(a), a.limit(0)),
        ("branching", tests(b.where("NOT contained")), tested),
        ("overlay", tests(a), a),
    ]
    out = None
    for method, region, containment in rows:
        one = region.crossJoin(F.broadcast(count(containment, "containment_tests"))).crossJoin(F.broadcast(hits)).select(F.lit(method).alias("method"), "region_tests", "containment_tests", "results")
        out = one if out is None else out.unionByName(one)
    return out


def region_trace(tree: RegionTree, rect) -> DataFrame:
    """(round, quads, pois) that the plain descent keeps in each round."""
    a = stored(open_quads(tree, rect), "open")
    q = a.where("round > 0").groupBy("round").agg(F.count("*").alias("quads"))
    p = tree.pois.where(overlaps(rect)).join(a, "quad").groupBy((F.col("round") + 1).alias("round")).agg(F.count("*").alias("pois"))
    return q.join(p, "round", "full").select(F.col("round").cast("int").alias("round"), F.coalesce("quads", F.lit(0)).alias("quads"), F.coalesce("pois", F.lit(0)).alias("pois"))


def many_regions(tree: RegionTree, rects: DataFrame) -> DataFrame:
    """rects (rect, x0, y0, x1, y1), small: the branching descent for all of them at once; rect, pois."""
    spark = tree.quads.sparkSession
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")
    fits = "c.bl_x >= x0 AND c.bl_y >= y0 AND c.tr_x <= x1 AND c.tr_y <= y1"
    meets = "c.bl_x <= x1 AND c.bl_y <= y1 AND c.tr_x >= x0 AND c.tr_y >= y0"
    walk = spark.sql(
        f"WITH RECURSIVE walk(rect, x0, y0, x1, y1, quad, contained) AS (SELECT rect, x0, y0, x1, y1, c.quad, {fits} FROM {{asked}} JOIN {{quads}} c ON c.parent IS NULL "
        f"UNION ALL SELECT w.rect, w.x0, w.y0, w.x1, w.y1, c.quad, w.contained OR ({fits}) FROM walk w JOIN {{quads}} c ON c.parent = w.quad WHERE w.contained OR ({meets})) SELECT * FROM walk",
        asked=rects,
        quads=tree.quads,
    )
    met = tree.pois.join(walk, "quad").where(F.col("contained") | overlaps([F.col(c) for c in ("x0", "y0", "x1", "y1")]))
    return met.groupBy("rect").agg(F.count("*").alias("pois"))
