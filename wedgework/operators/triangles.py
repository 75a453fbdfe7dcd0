"""Triangles: listing, counts for edges, vertices and the whole graph, directed closed pairs, triplets.

The default plan orients every edge from lower to higher (degree, id) and intersects the two out-lists of each oriented edge, which finds
each triangle once and credits its ends. A list has at most sqrt(2m) entries (36 MB at 10^13 edges), so no row outgrows a task, and a wedge
costs 16 bytes of shuffled list instead of a row. ``plan='relational'`` lists by three equi-joins that spill, for graphs beyond that. Vertices
that aren't numbers get dense ids first. The plans that take each arc's two whole lists (the kernels and fetch plans) give the same
numbers and exist to be compared with it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import Graph
from ..sources.tables import settle
from . import cells
from .intersect import arc_lists, met_lists
from .prep import compact, named, orient, oriented_lists


def _corners(g: Graph) -> DataFrame:
    """u, v, ws for every oriented edge: the far corners of the triangles that it is the lowest edge of."""
    lists = settle(oriented_lists(g), "oriented")
    return met_lists(lists).select(F.col("src").alias("u"), F.col("dst").alias("v"), F.array_intersect("a", "b").alias("ws"))


def listing(g: Graph, plan: str = "lists") -> DataFrame:
    """a < b < c of every triangle, once."""
    if plan == "lists" and cells.usable(g):
        return cells.corners(g).select("a", "b", F.explode("cs").alias("c"))
    if plan == "lists":
        corners = _corners(g).select("u", "v", F.explode("ws").alias("w"))
    else:
        e = orient(g, rank=True)
        # the two far ends in the order of the orientation: only that arc can close the wedge
        wedges = e.join(e.select("u", F.col("v").alias("w"), F.col("d").alias("dw")), "u").where("d < dw OR (d = dw AND v < w)").select("u", "v", "w")
        corners = wedges.join(e.select(F.col("u").alias("v"), F.col("v").alias("w")), ["v", "w"])
    s = F.array_sort(F.array("u", "v", "w"))
    return corners.select(s[0].alias("a"), s[1].alias("b"), s[2].alias("c"))


def count(g: Graph, plan: str = "lists") -> DataFrame:
    """One row: triangles."""
    if plan == "lists" and g.groups is not None and not g.directed and (found := cells.count(g)) is not None:
        return found
    g, _ = compact(g)
    if plan == "lists":
        return _corners(g).agg(F.coalesce(F.sum(F.size("ws").cast("long")), F.lit(0)).alias("triangles"))
    return listing(g, plan).agg(F.count(F.lit(1)).alias("triangles"))


def per_vertex(g: Graph, offset: bool = True, plan: str = "lists") -> DataFrame:
    """v, triangles for vertices with any. ``offset=False`` counts both orders of the two other corners, as an enumeration without the upper-triangle rule does."""
    if plan == "lists" and cells.usable(g):
        return cells.per_vertex(g).select("v", (F.col("triangles") * (1 if offset else 2)).alias("triangles"))
    g, index = compact(g)
    if plan == "lists":  # an edge's ends get its triangles at once
        own = "concat(array(named_struct('v', u, 'n', bigint(size(ws))), named_struct('v', v, 'n', bigint(size(ws)))), transform(ws, w -> named_struct('v', w, 'n', 1L)))"
        credits = _corners(g).where(F.size("ws") > 0).select(F.explode(F.expr(own)).alias("e")).select("e.v", "e.n")
    else:
        credits = listing(g, plan).select(F.explode(F.array("a", "b", "c")).alias("v"), F.lit(1).cast("long").alias("n"))
    return named(credits.groupBy("v").agg((F.sum("n") * (1 if offset else 2)).alias("triangles")), index)


def per_vertex_lists(g: Graph, offset: bool = True) -> DataFrame:
    """The same by each arc's two whole lists: with ``offset`` only common neighbours beyond dst are counted."""
    if offset and cells.usable(g):
        return cells.per_vertex(g, upper=True)
    both = arc_lists(g).withColumnsRenamed({"a": "ni", "b": "nj"})
    other = F.expr("slice(nj, int(array_position(nj, element_at(filter(nj, x -> x > dst), 1))), size(nj))") if offset else F.col("nj")
    usable = F.expr("size(nj) > 0 AND nj[size(nj) - 1] > dst") if offset else F.lit(True)
    return both.where(usable).withColumn("c", F.size(F.array_intersect("ni", other))).groupBy(F.col("src").alias("v")).agg(F.sum("c").cast("long").alias("triangles")).where("triangles > 0")


def edge_support(g: Graph) -> DataFrame:
    """src, dst, common: common neighbours of each arc of an undirected graph (0 where there are none)."""
    if cells.usable(g):
        return cells.edge_support(g)
    if g.lists is not None:  # dense: there are far more triangles than arcs, so each edge meets both whole lists
        met = arc_lists(g).where("src < dst").select("src", "dst", F.size(F.array_intersect("a", "b")).cast("long").alias("common"))
        ends = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
        return met.select("common", F.explode(ends).alias("e")).select("e.src", "e.dst", "common")
    t = listing(g)
    pairs = t.select(F.explode(F.array(F.struct(F.col("a").alias("x"), F.col("b").alias("y")), F.struct(F.col("a").alias("x"), F.col("c").alias("y")), F.struct(F.col("b").alias("x"), F.col("c").alias("y")))).alias("e"))
    closed = pairs.groupBy("e.x", "e.y").agg(F.count(F.lit(1)).alias("n"))
    arcs = g.arcs.select("src", "dst", F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y"))
    return arcs.join(closed, ["x", "y"], "left").select("src", "dst", F.coalesce("n", F.lit(0)).alias("common"))


def closed_pairs(g: Graph) -> DataFrame:
    """v, closed_pairs of a directed graph: ordered pairs of out-neighbours joined by an arc. One undirected listing, then three direction masks."""
    g, index = compact(g)
    masks = g.arcs.select(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y"), F.when(F.col("src") < F.col("dst"), 1).otherwise(2).alias("m")).groupBy("x", "y").agg(F.sum("m").cast("int").alias("m"))

    def side(t: DataFrame, x: str, y: str, name: str) -> DataFrame:
        return t.join(masks.select(F.col("x").alias(x), F.col("y").alias(y), F.col("m").alias(name)), [x, y])

    t = side(side(side(listing(g), "a", "b", "ab"), "a", "c", "ac"), "b", "c", "bc")
    fwd = lambda m: F.col(m).bitwiseAND(F.lit(1))
    bwd = lambda m: F.shiftright(F.col(m), 1)
    arcs_between = {"bc": fwd("bc") + bwd("bc"), "ac": fwd("ac") + bwd("ac"), "ab": fwd("ab") + bwd("ab")}
    credit = F.array(
        F.struct(F.col("a").alias("v"), (fwd("ab") * fwd("ac") * arcs_between["bc"]).alias("n")),
        F.struct(F.col("b").alias("v"), (bwd("ab") * fwd("bc") * arcs_between["ac"]).alias("n")),
        F.struct(F.col("c").alias("v"), (bwd("ac") * bwd("bc") * arcs_between["ab"]).alias("n")),
    )
    return named(t.select(F.explode(credit).alias("e")).where("e.n > 0").groupBy("e.v").agg(F.sum("e.n").alias("closed_pairs")), index)


def closed_pairs_joined(g: Graph) -> DataFrame:
    """The same by a plain three-way join on arcs."""
    a = g.arcs.select(F.col("src").alias("v"), F.col("dst").alias("j"))
    b = g.arcs.select(F.col("src").alias("v"), F.col("dst").alias("k"))
    c = g.arcs.select(F.col("src").alias("j"), F.col("dst").alias("k"))
    return a.join(b, "v").where("j != k").join(c, ["j", "k"]).groupBy("v").agg(F.count(F.lit(1)).alias("closed_pairs"))


def triplets(g: Graph) -> DataFrame:
    """v, closed, open: triplets centred at each vertex of an undirected graph, from degrees and triangles (no wedge is formed)."""
    deg = g.arcs.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg"))
    closed = F.coalesce("triangles", F.lit(0))
    return deg.join(per_vertex(g), "v", "left").select("v", closed.alias("closed"), (F.expr("deg * (deg - 1) div 2") - closed).alias("open"))
