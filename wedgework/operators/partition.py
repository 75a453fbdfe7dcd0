"""Vertex partitions: (v, idx, part), cut and balance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import Graph
from .prep import degrees, dense_index, sent, vertices


def _n(index: DataFrame) -> int:
    return index.agg(F.count(F.lit(1))).first()[0]


def block(g: Graph, p: int, index: DataFrame | None = None, rounding: str = "interval") -> DataFrame:
    """Contiguous equal-count blocks of the dense index. 'interval': vertex i of n (from 1) goes to the part ceil(i p / n); 'floor': idx p div n (idx from 0)."""
    index = dense_index(vertices(g)) if index is None else index
    n = _n(index)
    part = F.expr(f"((idx + 1) * {p} + {n} - 1) div {n} - 1") if rounding == "interval" else F.expr(f"(idx * {p}) div {max(n, 1)}")
    return index.select("v", "idx", (part if n else F.lit(0)).cast("int").alias("part"))


def by_degree(g: Graph) -> DataFrame:
    """v, idx in descending order of degree (ties: v)."""
    keyed = degrees(g).select(F.struct((-F.col("deg_out")).alias("d"), "v").alias("v"))
    return dense_index(keyed).select(F.col("v.v").alias("v"), "idx")


def cyclic(g: Graph, p: int, order: str = "degree") -> DataFrame:
    """Dealt out in turn over the degree order (or the id order)."""
    index = by_degree(g) if order == "degree" else dense_index(vertices(g))
    return index.select("v", "idx", (F.col("idx") % p).cast("int").alias("part"))


def balanced(g: Graph, p: int, weight: str = "deg_out") -> DataFrame:
    """Contiguous blocks of about equal weight: running sums within each index range, shifted by the ranges' totals (one row a range reaches the driver)."""
    from pyspark.sql import Window as W

    index = dense_index(vertices(g)).join(degrees(g), "v").select("v", "idx", F.expr(weight).alias("w"))
    n = _n(index)
    width = max(1, -(-n // 256))
    ranged = index.withColumn("r", F.expr(f"idx div {width}"))
    totals = sorted((r.r, r.w) for r in ranged.groupBy("r").agg(F.sum("w").alias("w")).collect())
    shifts, total = [], 0
    for r, w in totals:
        shifts.append((r, total))
        total += w
    before = F.coalesce(F.sum("w").over(W.partitionBy("r").orderBy("idx").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)) + F.col("s")
    placed = ranged.join(F.broadcast(g.spark.createDataFrame(shifts or [(0, 0)], "r long, s long")), "r")
    return placed.select("v", "idx", F.least(F.expr(f"0L + {p - 1}"), (before * p / F.lit(max(total, 1))).cast("long")).cast("int").alias("part"))


def hashed(g: Graph, p: int) -> DataFrame:
    """By the first 32 bits of md5 of the id, so that every engine deals alike."""
    h = F.conv(F.substring(F.md5(F.col("v").cast("string")), 1, 8), 16, 10).cast("long")
    return dense_index(vertices(g)).select("v", "idx", (h % p).cast("int").alias("part"))


SCHEMES = {"block": block, "cyclic": cyclic, "balanced": balanced, "hashed": hashed}


def arcs_with_parts(g: Graph, parts: DataFrame) -> DataFrame:
    n = parts.count()
    a = parts.select(F.col("v").alias("src"), F.col("part").alias("ps"))
    b = parts.select(F.col("v").alias("dst"), F.col("part").alias("pd"))
    return g.arcs.join(sent(a, n), "src").join(sent(b, n), "dst")


def cut_stats(g: Graph, parts: DataFrame) -> DataFrame:
    """One row: arcs, arcs between parts and their share."""
    cut = (F.col("ps") != F.col("pd")).cast("long")
    return arcs_with_parts(g, parts).agg(F.count(F.lit(1)).alias("n_arcs"), F.sum(cut).alias("n_cut"), F.round(F.avg(cut), 6).alias("cut_share"))


def imbalance(g: Graph, parts: DataFrame) -> DataFrame:
    """One row: largest and mean work of a part (summed list lengths of its arcs' two ends), their ratio, and the idle share of the lightest part."""
    deg = degrees(g).select("v", "deg_out")
    work = (
        g.arcs.join(deg.select(F.col("v").alias("src"), F.col("deg_out").alias("di")), "src")
        .join(deg.select(F.col("v").alias("dst"), F.col("deg_out").alias("dj")), "dst")
        .join(parts.select(F.col("v").alias("src"), "part"), "src")
        .groupBy("part")
        .agg(F.sum(F.col("di") + F.col("dj")).alias("work"), F.count(F.lit(1)).alias("arcs"))
    )
    n_parts = parts.agg(F.countDistinct("part").alias("n_parts"))
    one = work.agg(F.max("work").alias("max_work"), F.sum("work").alias("all_work"), F.max("arcs").alias("max_arcs"))
    return one.join(n_parts, how="cross").select("n_parts", "max_work", "all_work", "max_arcs", F.round(F.col("max_work") * F.col("n_parts") / F.col("all_work"), 6).alias("max_over_mean"))
