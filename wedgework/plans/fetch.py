"""How neighbour lists reach the arcs: the plans that stand for remote reads, with and without caching.

``halo`` ships each list once to each part that needs it; ``hot`` broadcasts the largest lists under a budget and joins the rest; both
are what an unlimited, and a degree-scored, read cache come to in a shuffle engine. ``auto`` decides from degree sums alone.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.csr import adjacency
from ..operators.intersect import edge_support as by_kernel
from ..operators.partition import SCHEMES, arcs_with_parts, block
from ..operators.prep import degrees
from ..operators.triangles import edge_support as by_listing
from ..schema import Graph

#: Bytes of lists that are broadcast at most.
HOT_BYTES = 64 << 20


@dataclass(frozen=True)
class FetchPlan:
    kind: str
    per_arc_bytes: int
    halo_bytes: int
    wedges: int
    hot_share: float

    def explain(self) -> str:
        return f"{self.kind}: lists per arc {self.per_arc_bytes} B, once per part {self.halo_bytes} B, oriented wedges {self.wedges}, hot share {self.hot_share:.2f}"


def estimates(g: Graph, p: int) -> DataFrame:
    """One row of byte estimates from degrees: lists per arc, each list once per part at most, and vertices' hot gains."""
    d = degrees(g)
    return d.agg(
        (8 * F.sum(F.col("deg_in") * F.col("deg_out"))).alias("per_arc_bytes"), (8 * F.sum(F.least(F.lit(p), F.col("deg_in")) * F.col("deg_out"))).alias("halo_bytes"), F.sum("deg_out").alias("n_arcs"), F.count(F.lit(1)).alias("n"),
    )


def hot_threshold(g: Graph, budget: int = HOT_BYTES, id_bytes: int = 8) -> tuple[int, int]:
    """(degree, bytes): lists of at least this degree fit the budget; decided on the histogram of degrees.

    Ids that aren't numbers count with the bytes that they have, and a list with its 24 bytes of row.
    """
    if dict(g.arcs.dtypes)["dst"] == "string":
        sizes = g.arcs.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg_out"), (F.sum(F.octet_length("dst") + id_bytes) + 24).alias("b"))
    else:
        sizes = degrees(g).select("deg_out", (F.col("deg_out") * id_bytes).alias("b"))
    hist = sorted(((r.deg_out, r.b) for r in sizes.where("deg_out > 0").groupBy("deg_out").agg(F.sum("b").alias("b")).collect()), reverse=True)
    used, edge = 0, (hist[0][0] + 1) if hist else 1
    for d, b in hist:
        if used + b > budget:
            break
        used, edge = used + b, d
    return max(edge, 1), used


def plan(g: Graph, p: int = 200, budget: int = HOT_BYTES) -> FetchPlan:
    from ..operators.prep import oriented_degrees

    e = estimates(g, p).first()
    out = oriented_degrees(g)
    wedges = int(out.agg(F.sum(F.expr("d * (d - 1) div 2"))).first()[0] or 0)
    edge, _ = hot_threshold(g, budget)
    hot = degrees(g).where(F.col("deg_out") >= edge).agg(F.sum(F.col("deg_in") * F.col("deg_out"))).first()[0] or 0
    share = 8 * hot / max(e.per_arc_bytes or 0, 1)
    kind = "relational" if not g.directed and 16 * wedges <= (e.per_arc_bytes or 0) else "hot" if share > 0.3 else "halo"
    return FetchPlan(kind, int(e.per_arc_bytes or 0), int(e.halo_bytes or 0), wedges, float(share))


def attach(g: Graph, kind: str = "per_arc", p: int = 8, budget: int = HOT_BYTES, parts: DataFrame | None = None) -> DataFrame:
    """src, dst, a, b: every arc with both lists, fetched by the plan of that name."""
    lists = adjacency(g).select("v", "nbrs")
    own = lists.select(F.col("v").alias("src"), F.col("nbrs").alias("a"))
    far = lists.select(F.col("v").alias("dst"), F.col("nbrs").alias("b"))
    if kind == "per_arc":
        return g.arcs.join(own, "src").join(far, "dst").select("src", "dst", "a", "b")
    if kind == "two_step":  # the offset pair first, then the list under its address
        offsets = lists.select(F.col("v").alias("dst"), F.xxhash64("v").alias("address"), F.size("nbrs").alias("length"))
        stored = lists.select(F.xxhash64("v").alias("address"), F.col("v").alias("dst"), F.col("nbrs").alias("b"))
        return g.arcs.join(own, "src").join(offsets, "dst").where("length > 0").join(stored, ["address", "dst"]).select("src", "dst", "a", "b")
    if kind == "halo":
        parts = block(g, p) if parts is None else parts
        placed = arcs_with_parts(g, parts).select(F.col("ps").alias("part"), "src", "dst")
        needed = placed.select("part", "dst").distinct().join(far, "dst")
        return placed.join(needed, ["part", "dst"]).join(own, "src").select("src", "dst", "a", "b")
    if kind == "hot":
        edge, _ = hot_threshold(g, budget)
        hot = far.where(F.size("b") >= edge)  # at most ``budget`` bytes by construction
        cold = far.where(F.size("b") < edge)
        named = F.broadcast(hot.select("dst"))
        mine = g.arcs.join(own, "src")
        return mine.join(F.broadcast(hot), "dst").select("src", "dst", "a", "b").unionByName(mine.join(named, "dst", "left_anti").join(cold, "dst").select("src", "dst", "a", "b"))
    raise ValueError(kind)


def edge_support(g: Graph, fetch: str = "auto", kernel: str = "builtin", p: int = 8, budget: int = HOT_BYTES) -> DataFrame:
    """src, dst, common by a fetch plan and a kernel."""
    if fetch == "auto":
        fetch = plan(g, p, budget).kind
    if fetch == "relational":
        return by_kernel(g, "relational") if g.directed else by_listing(g)
    rows = attach(g, fetch, p, budget)
    if kernel == "builtin":
        found = rows.select("src", "dst", F.size(F.array_intersect("a", "b")).cast("long").alias("common"))
    else:
        from ..operators.intersect import arrow_common

        found = arrow_common(rows, kernel)
    return found


def run(g: Graph, p: int = 8, plan_kind: str = "halo", scheme: str = "block", kernel: str = "builtin", budget: int = HOT_BYTES) -> DataFrame:
    """part, v, deg, closed, lcc: each part works on its own vertices' arcs, with far lists fetched by the plan of that name.

    An arc's common neighbours, summed over a vertex's arcs, are its closed ordered pairs (twice its triangles in an undirected graph).
    """
    parts = SCHEMES[scheme](g, p)
    rows = attach(g, plan_kind, p, budget, parts) if plan_kind != "relational" else None
    if rows is None:
        found = edge_support(g, "relational")
    elif kernel == "builtin":
        found = rows.select("src", "dst", F.size(F.array_intersect("a", "b")).cast("long").alias("common"))
    else:
        from ..operators.intersect import arrow_common

        found = arrow_common(rows, kernel)
    deg = g.arcs.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg"))
    closed = found.groupBy(F.col("src").alias("v")).agg(F.sum("common").alias("closed"))
    own = parts.select("v", "part").join(deg, "v").join(closed, "v", "left").withColumn("closed", F.coalesce("closed", F.lit(0)))
    return own.select("part", "v", "deg", "closed", F.when(F.col("deg") >= 2, F.lit(1.0) * F.col("closed") / (F.col("deg") * (F.col("deg") - 1))).alias("lcc"))


def shipped(g: Graph, p: int = 8, budget: int = 64 << 10) -> DataFrame:
    """plan, ids: list entries that each plan moves between parts (block scheme)."""
    parts = block(g, p)
    deg = degrees(g).select(F.col("v").alias("dst"), F.col("deg_out").alias("d"))
    cut = arcs_with_parts(g, parts).where("ps != pd").select(F.col("ps").alias("part"), "dst").join(deg, "dst")
    once = cut.distinct()
    edge, used = hot_threshold(g, budget)
    rows = [
        cut.agg(F.coalesce(F.sum("d"), F.lit(0)).alias("ids")).select(F.lit("per_arc").alias("plan"), "ids"),
        cut.agg(F.coalesce(F.sum(F.col("d") + 2), F.lit(0)).alias("ids")).select(F.lit("two_step").alias("plan"), "ids"),
        once.agg(F.coalesce(F.sum("d"), F.lit(0)).alias("ids")).select(F.lit("halo").alias("plan"), "ids"),
        cut.where(F.col("d") < edge).agg((F.coalesce(F.sum("d"), F.lit(0)) + F.lit(used // 8 * p)).alias("ids")).select(F.lit("hot").alias("plan"), "ids"),
    ]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out
