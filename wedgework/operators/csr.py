"""Adjacency lists, compressed sparse rows and their sizes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..schema import Graph
from .prep import vertices


def adjacency(g: Graph, chunk: int | None = None) -> DataFrame:
    """v, deg, chunk, nbrs (ascending out-neighbours). With ``chunk``, lists are cut before they are gathered, so no row outgrows it.

    A graph that comes as lists has them already: nothing is moved.
    """
    if g.lists is not None:
        lists = g.lists.select("v", F.size("nbrs").cast("long").alias("deg"), "nbrs")
        if not chunk:
            return lists.select("v", "deg", F.lit(0).alias("chunk"), "nbrs")
        cut = F.expr(f"transform(sequence(0, int((deg - 1) div {chunk})), i -> slice(nbrs, i * {chunk} + 1, {chunk}))")
        return lists.select("v", "deg", F.posexplode(cut).alias("chunk", "nbrs"))
    if not chunk:
        lists = g.arcs.groupBy(F.col("src").alias("v")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))
        return lists.select("v", F.size("nbrs").cast("long").alias("deg"), F.lit(0).alias("chunk"), "nbrs")
    by = W.partitionBy("src")
    ranked = g.arcs.select(F.col("src").alias("v"), "dst", (F.row_number().over(by.orderBy("dst")) - 1).alias("r"), F.count(F.lit(1)).over(by).alias("deg"))
    cut = ranked.withColumn("chunk", F.expr(f"int(r div {chunk})"))
    return cut.groupBy("v", "deg", "chunk").agg(F.sort_array(F.collect_list("dst")).alias("nbrs")).select("v", "deg", "chunk", "nbrs")


#: Arcs of one row of compressed rows, about; a vertex isn't split.
GROUP = 1 << 20


def to_csr(g: Graph, parts: DataFrame, group: int = GROUP) -> DataFrame:
    """part, first (its lowest index), offsets, adjacencies for vertices that have (v, idx, part); neighbours as indices. A part comes in groups of vertices of bounded size."""
    a = parts.select(F.col("v").alias("src"), F.col("idx").alias("i"), "part")
    b = parts.select(F.col("v").alias("dst"), F.col("idx").alias("j"))
    arcs = g.arcs.join(a, "src").join(b, "dst").select("part", "i", "j")
    rows = arcs.unionByName(parts.select("part", F.col("idx").alias("i"), F.lit(None).cast("long").alias("j")))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        part, i, j = None, np.zeros(0, dtype=np.int64), np.zeros(0)

        def ended(i: np.ndarray, j: np.ndarray) -> pd.DataFrame:
            first, last = int(i.min()), int(i.max())
            real = ~np.isnan(j)
            counts = np.bincount((i[real] - first).astype(np.int64), minlength=last - first + 1)
            return pd.DataFrame({"part": [part], "first": [first], "offsets": [np.concatenate([[0], np.cumsum(counts)])], "adjacencies": [j[real].astype(np.int64)]})

        for b in batches:
            for p, rows in b.groupby("part", sort=True):
                if part is not None and p != part:
                    yield ended(i, j)
                    i, j = i[:0], j[:0]
                part = p
                i, j = np.concatenate([i, rows["i"].to_numpy(np.int64)]), np.concatenate([j, rows["j"].to_numpy(np.float64)])
                if len(i) > group and (whole := np.searchsorted(i, i[-1])):  # the last vertex may go on
                    yield ended(i[:whole], j[:whole])
                    i, j = i[whole:], j[whole:]
        if part is not None:
            yield ended(i, j)

    return rows.repartition("part").sortWithinPartitions("part", "i", "j").mapInPandas(run, "part int, first long, offsets array<long>, adjacencies array<long>")


def from_csr(csr: DataFrame) -> DataFrame:
    """Arcs (indices) of compressed rows."""
    rows = csr.select("first", "adjacencies", "offsets", F.posexplode(F.expr("slice(offsets, 1, size(offsets) - 1)")).alias("k", "lo"))
    lists = rows.select((F.col("first") + F.col("k")).alias("src"), F.expr("slice(adjacencies, int(lo) + 1, int(offsets[k + 1] - lo))").alias("nbrs"))
    return lists.select("src", F.explode("nbrs").alias("dst"))


def size_bytes(g: Graph, id_bytes: int = 4) -> DataFrame:
    """One row: n, arcs and the bytes of offsets and adjacencies."""
    n = vertices(g).agg(F.count(F.lit(1)).alias("n"))
    return n.join(g.arcs.agg(F.count(F.lit(1)).alias("n_arcs")), how="cross").withColumn("csr_bytes", F.lit(id_bytes) * (F.col("n") + 1 + F.col("n_arcs")))
