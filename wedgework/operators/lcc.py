"""Local clustering coefficients and what users derive from them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..schema import Graph
from .prep import neighbours, symmetrize
from .triangles import closed_pairs, listing, per_vertex


def local_clustering(g: Graph, isolated: str = "null", only: DataFrame | None = None, degrees_of: Graph | None = None) -> DataFrame:
    """v, deg, closed, lcc.

    Undirected: 2 T / (d (d - 1)); directed: closed ordered pairs / (d (d - 1)) with d the out-degree. Vertices of degree under two get
    null, 0.0 ('zero') or no row ('drop'). ``only`` (v) restricts the result, and the work, to those vertices. ``degrees_of``
    takes degrees from another graph, for example the one before pruning.
    """
    of = degrees_of or g
    deg = of.arcs.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg")) if of.lists is None else neighbours(of)
    if only is not None:
        deg = deg.join(only.select("v").distinct(), "v", "left_semi")
        near = g.arcs.join(only.select(F.col("v").alias("src")).distinct(), "src", "left_semi")
        # a triangle of a chosen vertex lies among it and its neighbours
        keep = near.select(F.explode(F.array("src", "dst")).alias("x")).distinct()
        small = g.arcs.join(keep, F.col("src") == F.col("x"), "left_semi").join(keep, F.col("dst") == F.col("x"), "left_semi")
        if g.directed:  # the mask plan needs the arcs of all three sides
            g = g.with_arcs(small)
        else:
            g = symmetrize(g.with_arcs(small))
    closed = closed_pairs(g).withColumnRenamed("closed_pairs", "closed") if g.directed else per_vertex(g).withColumnRenamed("triangles", "closed")
    rows = deg.join(closed, "v", "left").withColumn("closed", F.coalesce("closed", F.lit(0)))
    value = F.lit(1.0 if g.directed else 2.0) * F.col("closed") / (F.col("deg") * (F.col("deg") - 1))
    rows = rows.withColumn("lcc", F.when(F.col("deg") >= 2, value).otherwise(F.lit(0.0) if isolated == "zero" else F.lit(None)))
    return rows.where("deg >= 2") if isolated == "drop" else rows


def where(scores: DataFrame, min_degree: int = 0, ids: DataFrame | None = None) -> DataFrame:
    out = scores.where(F.col("deg") >= min_degree)
    return out if ids is None else out.join(ids.select("v"), "v", "left_semi")


def top(scores: DataFrame, k: int, by: str = "lcc", group: str | None = None) -> DataFrame:
    """The k largest (ties: smaller v), over all or in each group."""
    if group is None:
        return scores.orderBy(F.desc_nulls_last(by), "v").limit(k)
    w = W.partitionBy(group).orderBy(F.desc_nulls_last(by), "v")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def summary(g: Graph) -> DataFrame:
    """One row: vertices of degree >= 2, mean coefficient over them, triangles, wedges, transitivity."""
    s = local_clustering(g)
    pairs = F.expr("deg * (deg - 1)") if g.directed else F.expr("deg * (deg - 1) div 2")
    return s.agg(
        F.sum((F.col("deg") >= 2).cast("long")).alias("n_vertices"), F.round(F.avg("lcc"), 6).alias("mean_lcc"), F.sum("closed").alias("closed"), F.sum(pairs).alias("wedges"),
        F.round(F.sum("closed") / F.sum(pairs), 6).alias("transitivity"),
    )


def histogram(scores: DataFrame, bins: int = 10) -> DataFrame:
    bucket = F.least(F.floor(F.col("lcc") * bins), F.lit(bins - 1)).cast("int")
    return scores.where("lcc IS NOT NULL").groupBy(bucket.alias("bin")).agg(F.count(F.lit(1)).alias("n_vertices"))


def core_frontier(g: Graph, low: float = 0.3, high: float = 0.7) -> DataFrame:
    """v, deg, role: vertices in the centre of a cluster (high coefficient), at its frontier (low), or between."""
    s = local_clustering(g, isolated="drop")
    return s.select("v", "deg", F.when(F.col("lcc") >= high, "core").when(F.col("lcc") <= low, "frontier").otherwise("between").alias("role"))


def recommend_links(g: Graph, k: int = 3, most_degree: int | None = None) -> DataFrame:
    """v, other, common, rank: the k vertices with most common neighbours that v isn't linked with (ties: smaller id). ``most_degree`` leaves hubs out as go-betweens.

    Without it the result is exact and forms every open wedge: a hub of degree d makes d^2 rows, so set it on graphs with hubs.
    """
    arcs = g.arcs
    if most_degree:
        hubs = arcs.groupBy(F.col("src").alias("h")).count().where(F.col("count") > most_degree).select("h")
        arcs = arcs.join(hubs, F.col("src") == F.col("h"), "left_anti")
    a = arcs.select(F.col("src").alias("m"), F.col("dst").alias("v"))
    b = arcs.select(F.col("src").alias("m"), F.col("dst").alias("other"))
    found = a.join(b, "m").where("v != other").groupBy("v", "other").agg(F.count(F.lit(1)).alias("common"))
    new = found.join(g.arcs.select(F.col("src").alias("v"), F.col("dst").alias("other")), ["v", "other"], "left_anti")
    w = W.partitionBy("v").orderBy(F.desc("common"), "other")
    return new.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("v", "other", "common", "rank")


def triangles_of(g: Graph, only: DataFrame) -> DataFrame:
    """The triangles with a corner among the given vertices."""
    t = listing(g)
    hit = t.select("a", "b", "c", F.explode(F.array("a", "b", "c")).alias("v")).join(only.select("v"), "v", "left_semi")
    return hit.select("a", "b", "c").distinct()
