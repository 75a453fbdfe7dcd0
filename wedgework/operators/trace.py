"""The ordered remote reads of each part, and the measures of their reuse."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..schema import Graph
from ..sources.tables import settle
from . import cells
from .partition import arcs_with_parts
from .prep import SENT_VERTICES, degrees, dense_index


def remote(g: Graph, parts: DataFrame) -> DataFrame:
    """part, src, dst of the arcs whose far list lies in another part."""
    return arcs_with_parts(g, parts).where("ps != pd").select(F.col("ps").alias("part"), "src", "dst")


def build(g: Graph, parts: DataFrame, id_bytes: int = 4) -> DataFrame:
    """part, seq, src, dst, off_bytes, adj_bytes, deg, deg_in: a part reads in the order of its arcs; a read is an offset pair, then a list."""
    deg = degrees(g).select(F.col("v").alias("dst"), F.col("deg_out").alias("deg"), "deg_in")
    order = W.partitionBy("part").orderBy("src", "dst")
    return remote(g, parts).join(deg, "dst").select(
        "part", (F.row_number().over(order) - 1).cast("long").alias("seq"), "src", "dst", F.lit(2 * id_bytes).alias("off_bytes"), (F.col("deg") * id_bytes).alias("adj_bytes"), "deg", "deg_in"
    )


def _met(g: Graph, parts: DataFrame) -> DataFrame:
    """part, dst, deg, c: how often each part reads a far list, and how long that is.

    Where lists come from the source and the parts of their vertices fit a task, a list itself tells in which parts its readers are:
    nothing is moved. Lists of few vertices aren't made at all, their groups tell it.
    """
    deg = degrees(g).select(F.col("v").alias("dst"), F.col("deg_out").alias("deg"))
    if g.lists is None or g.directed or parts.count() > SENT_VERTICES:
        return remote(g, parts).groupBy("part", "dst").agg(F.count(F.lit(1)).alias("c")).join(deg, "dst").select("part", "dst", "deg", "c")
    of = parts.select("v", "part").toArrow().sort_by("v")
    names, part = of["v"].to_numpy(), of["part"].to_numpy()
    n_parts = int(part.max(initial=0)) + 1
    if cells.usable(g) and len(names) * n_parts <= 4 * SENT_VERTICES:
        return cells.reads(g, names, part)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            nbrs, v = b.column("nbrs"), b.column("v").to_numpy()
            ends = nbrs.offsets.to_numpy().astype(np.int64)
            near = part[np.searchsorted(names, nbrs.values.to_numpy()[ends[0] : ends[-1]])]
            at = np.repeat(np.arange(len(v)) * n_parts, np.diff(ends)) + near
            c = np.bincount(at, minlength=len(v) * n_parts).reshape(len(v), n_parts)
            c[np.arange(len(v)), part[np.searchsorted(names, v)]] = 0
            i, p = np.nonzero(c)
            yield pa.RecordBatch.from_arrays([pa.array(p.astype(np.int32)), pa.array(v[i]), pa.array(np.diff(ends)[i]), pa.array(c[i, p].astype(np.int64))], ["part", "dst", "deg", "c"])

    return g.lists.select("v", "nbrs").mapInArrow(run, "part int, dst long, deg long, c long")


def read_counts(g: Graph, parts: DataFrame) -> DataFrame:
    """part, n_local, n_remote."""
    cut = (F.col("ps") != F.col("pd")).cast("long")
    return arcs_with_parts(g, parts).groupBy(F.col("ps").alias("part")).agg(F.sum(1 - cut).alias("n_local"), F.sum(cut).alias("n_remote"))


def compulsory(g: Graph, parts: DataFrame) -> DataFrame:
    """One row: remote reads, first touches (distinct part and target) and their share: the misses of a cache without limits."""
    met = remote(g, parts).groupBy("part", "dst").agg(F.count(F.lit(1)).alias("c"))
    return met.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n_remote"), F.count(F.lit(1)).alias("n_first")).withColumn("share", F.round(F.col("n_first") / F.col("n_remote"), 6))


def repeat_histogram(g: Graph, parts: DataFrame) -> DataFrame:
    """repeats, n_targets: how many (part, target) are read that often."""
    return remote(g, parts).groupBy("part", "dst").agg(F.count(F.lit(1)).alias("repeats")).groupBy("repeats").agg(F.count(F.lit(1)).alias("n_targets"))


def top_share(g: Graph, parts: DataFrame, percent: int = 10) -> DataFrame:
    """One row: remote reads, and those of the top share of vertices by degree (ties: smaller id)."""
    deg = settle(degrees(g).select("v", F.col("deg_in").alias("d")), "degrees")
    n = deg.count()
    # the degree at which the top begins comes from a histogram; only its ties are ordered by id
    counts = sorted(((r.d, r.c) for r in deg.groupBy("d").agg(F.count(F.lit(1)).alias("c")).collect()), reverse=True)
    want, edge = n * percent // 100, None
    for d, c in counts:
        if want < c:
            edge = d
            break
        want -= c
    if edge is None:
        top = deg.select("v")
    else:
        tied = dense_index(deg.where(F.col("d") == edge)).where(F.col("idx") < want).select("v")
        top = deg.where(F.col("d") > edge).select("v").unionByName(tied)
    reads = remote(g, parts).groupBy("dst").agg(F.count(F.lit(1)).alias("c")).join(top.select(F.col("v").alias("dst"), F.lit(1).alias("hit")), "dst", "left")
    return reads.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n_remote"), F.coalesce(F.sum(F.col("c") * F.col("hit")), F.lit(0)).alias("n_top")).withColumn("share", F.round(F.col("n_top") / F.col("n_remote"), 6))


def reuse_vs_size(g: Graph, parts: DataFrame) -> DataFrame:
    """deg, n_targets, n_reads: how often lists of each size are read."""
    met = _met(g, parts)
    return met.groupBy("deg").agg(F.count(F.lit(1)).alias("n_targets"), F.sum("c").alias("n_reads"))


def reuse_correlation(g: Graph, parts: DataFrame) -> DataFrame:
    """One row: correlation of reads with list size (that with the size of an offset entry is undefined: all are equal)."""
    met = _met(g, parts)
    return met.agg(F.round(F.corr("c", "deg"), 5).alias("correlation"))


def expected_accesses(g: Graph, parts: DataFrame, p: int) -> DataFrame:
    """One row: mean reads of a read (part, target), against in-degree / p ('uniform') and in-degree / p - 1 ('printed')."""
    deg = degrees(g).select(F.col("v").alias("dst"), "deg_in")
    met = remote(g, parts).groupBy("part", "dst").agg(F.count(F.lit(1)).alias("c"))
    per = met.join(deg, "dst")
    return per.agg(F.round(F.avg("c"), 4).alias("measured"), F.round(F.avg(F.col("deg_in") / p), 4).alias("uniform"), F.round(F.avg(F.col("deg_in") / p - 1), 4).alias("printed"))
