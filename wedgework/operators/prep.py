"""Graph preparation: simplify, symmetrise, prune, relabel, dense ids, degrees, orientation."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import Graph
from ..sources.tables import settle


def simplify(arcs: DataFrame) -> DataFrame:
    """Without loops, nulls and repeated arcs."""
    return arcs.where("src != dst").select("src", "dst").distinct()


def symmetrize(g: Graph) -> Graph:
    back = g.arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return Graph(g.arcs.unionByName(back).distinct(), directed=False, name=g.name)


#: Vertices whose numbers (index, degree, part) are sent to every task, at most; beyond that arcs are joined with them.
SENT_VERTICES = 1 << 20


def sent(rows: DataFrame, n: int | None = None) -> DataFrame:
    """Rows (one a vertex, of few columns) marked for broadcast where they are few enough; ``n``: their number, where it is known."""
    return F.broadcast(rows) if (rows.count() if n is None else n) <= SENT_VERTICES else rows


def vertices(g: Graph) -> DataFrame:
    if g.ends is not None:
        return g.ends
    return g.arcs.select(F.explode(F.array("src", "dst")).alias("v")).distinct()


def degrees(g: Graph) -> DataFrame:
    """v, deg_out, deg_in: one shuffle of map-side sums."""
    if g.lists is not None and not g.directed:
        d = F.size("nbrs").cast("long")
        return g.lists.select("v", d.alias("deg_out"), d.alias("deg_in"))
    ends = g.arcs.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("v"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("e"))
    return ends.groupBy("e.v").agg(F.sum("e.o").alias("deg_out"), F.sum("e.i").alias("deg_in"))


def neighbours(g: Graph) -> DataFrame:
    """v, deg: distinct neighbours without direction."""
    if not g.directed:
        if g.lists is not None:
            return g.lists.select("v", F.size("nbrs").cast("long").alias("deg"))
        return g.arcs.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg"))
    return neighbours(symmetrize(g))


def degree_histogram(g: Graph) -> DataFrame:
    return degrees(g).groupBy("deg_out").agg(F.count(F.lit(1)).alias("n_vertices")).withColumnRenamed("deg_out", "deg")


def tail_slope(g: Graph, least: int = 2) -> DataFrame:
    """Exponent of a power law fitted to the degrees from ``least`` on (maximum likelihood)."""
    return degrees(g).where(F.col("deg_out") >= least).agg((1 + F.count(F.lit(1)) / F.sum(F.log(F.col("deg_out") / (least - 0.5)))).alias("exponent"))


def prune(g: Graph, rounds: int | None = 1, most: int = 1000) -> Graph:
    """Without vertices of fewer than two neighbours: once (1), several times, or until nothing changes (None: the 2-core)."""
    arcs, done = g.arcs, 0
    while done < (most if rounds is None else rounds):
        deg = neighbours(g.with_arcs(arcs))
        low = deg.where("deg < 2").select("v")
        if rounds is None:
            low = settle(low, "pendants")
            if low.isEmpty():
                break
        kept = arcs.join(low, F.col("src") == F.col("v"), "left_anti").join(low, F.col("dst") == F.col("v"), "left_anti")
        arcs = settle(kept, "pruned") if rounds is None else kept
        done += 1
    return g.with_arcs(arcs)


def dense_index(vs: DataFrame) -> DataFrame:
    """v, idx (0..n-1 in the order of v): a range shuffle and one count for each partition, no single-partition window."""
    spark = vs.sparkSession
    ranged = vs.select("v").repartitionByRange("v").sortWithinPartitions("v").withColumn("m", F.monotonically_increasing_id())
    ranged = settle(ranged, "ranged")  # both reads below must see the same partitions
    part, local = F.shiftright("m", 33), F.col("m").bitwiseAND(F.lit((1 << 33) - 1))
    sizes = {r.p: r.n for r in ranged.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()}  # one row a partition
    shifts, total = [], 0
    for p in sorted(sizes):
        shifts.append((p, total))
        total += sizes[p]
    if not shifts:
        return ranged.select("v", F.col("m").alias("idx"))
    return ranged.withColumn("p", part).join(F.broadcast(spark.createDataFrame(shifts, "p long, s long")), "p").select("v", (F.col("s") + local).alias("idx"))


def shuffled_index(vs: DataFrame, seed: str = "") -> DataFrame:
    """v, idx in a random but repeatable order: by md5 of seed and id."""
    keyed = vs.select(F.concat(F.md5(F.concat(F.lit(seed), F.col("v").cast("string"))), F.lit(":"), F.col("v").cast("string")).alias("v"), F.col("v").alias("of"))
    return dense_index(keyed).join(keyed, "v").select(F.col("of").alias("v"), "idx")


def renamed(g: Graph, index: DataFrame) -> Graph:
    a = index.select(F.col("v").alias("src"), F.col("idx").alias("s"))
    b = index.select(F.col("v").alias("dst"), F.col("idx").alias("t"))
    return g.with_arcs(g.arcs.join(a, "src").join(b, "dst").select(F.col("s").alias("src"), F.col("t").alias("dst")))


def relabel(g: Graph, seed: str = "", how: str = "hash") -> Graph:
    """Dense ids; how='hash': random order (breaks up degree-ordered inputs), how='order': the order of the old ids."""
    vs = vertices(g)
    return renamed(g, shuffled_index(vs, seed) if how == "hash" else dense_index(vs))


def compact(g: Graph) -> tuple[Graph, DataFrame | None]:
    """The graph with long ids, and its index (v, idx) where the vertices were something else: lists and joins then move 8 bytes a vertex."""
    if dict(g.arcs.dtypes)["src"] in ("bigint", "int"):
        return g, None
    g = g.with_arcs(settle(g.arcs, "arcs"))
    index = dense_index(vertices(g))
    return renamed(g, index), index


def named(rows: DataFrame, index: DataFrame | None, column: str = "v") -> DataFrame:
    """Rows with the vertices' own names again."""
    if index is None:
        return rows
    back = index.select(F.col("idx").alias(column), F.col("v").alias("name_"))
    return rows.join(back, column).select(*(F.col("name_").alias(column) if c == column else c for c in rows.columns))


def is_degree_ordered(g: Graph, threshold: float = 0.5) -> DataFrame:
    """One row: correlation of id and degree, and whether its size exceeds the threshold (then relabel)."""
    one = degrees(g).agg(F.round(F.coalesce(F.corr(F.col("v").cast("double"), F.col("deg_out").cast("double")), F.lit(0.0)), 6).alias("correlation"))
    return one.withColumn("degree_ordered", F.abs("correlation") > threshold)


def orient(g: Graph, rank: bool = False) -> DataFrame:
    """u, v (and d, the degree of v) for every edge, from the end of lower (degree, id) to the higher one: out-degrees are at most sqrt(2m)."""
    deg = neighbours(g)
    a = deg.select(F.col("v").alias("src"), F.col("deg").alias("ds"))
    b = deg.select(F.col("v").alias("dst"), F.col("deg").alias("dd"))
    arcs = symmetrize(g).arcs if g.directed else g.arcs
    return arcs.join(a, "src").join(b, "dst").where("ds < dd OR (ds = dd AND src < dst)").select(F.col("src").alias("u"), F.col("dst").alias("v"), *([F.col("dd").alias("d")] if rank else []))


def _oriented(g: Graph) -> DataFrame:
    """u, w of the oriented edges. Where lists come from the source, an edge isn't moved before it is known to stay."""
    if g.lists is None or g.directed:
        return orient(g).withColumnRenamed("v", "w")
    deg = settle(neighbours(g), "degrees")
    arcs = g.lists.select(F.col("v").alias("u"), F.size("nbrs").cast("long").alias("du"), F.explode("nbrs").alias("w"))
    return arcs.join(sent(deg.select(F.col("v").alias("w"), F.col("deg").alias("dw"))), "w").where("du < dw OR (du = dw AND u < w)").select("u", "w")


def oriented_lists(g: Graph) -> DataFrame:
    """v, nbrs: ends of the oriented edges from v."""
    return _oriented(g).groupBy(F.col("u").alias("v")).agg(F.sort_array(F.collect_list("w")).alias("nbrs"))


def oriented_degrees(g: Graph) -> DataFrame:
    """v, d: the lengths of these lists alone, in map-side sums."""
    return _oriented(g).groupBy(F.col("u").alias("v")).agg(F.count(F.lit(1)).alias("d"))
