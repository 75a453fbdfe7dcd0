"""User-facing functions: scalar and grouped pandas functions and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult, OrderingColumn, PartitioningColumn

from ..schema import CacheConfig
from .replay import ReadCache



@F.pandas_udf(T.LongType())
def common_count(a: pd.Series, b: pd.Series) -> pd.Series:
    """Size of the intersection of two ascending lists."""
    return pd.Series([len(np.intersect1d(x, y, assume_unique=True)) if x is not None and y is not None else 0 for x, y in zip(a, b, strict=True)])


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def median_ci(values: pd.Series) -> list:
    """[median, low, high]: the median with its 95 % bootstrap interval."""
    v = values.dropna().to_numpy(float)
    if not len(v):
        return []
    rng = np.random.default_rng(0)
    lo, hi = np.percentile(np.median(rng.choice(v, (500, len(v))), axis=1), [2.5, 97.5])
    return [float(np.median(v)), float(lo), float(hi)]


@F.udtf(returnType=T.StructType([T.StructField(x, T.LongType()) for x in ("src", "dst")]))
class RmatEdges:
    """rmat_edges(scale, edge_factor, slice, slices): the draws of one slice of the recursive-matrix generator."""

    def eval(self, scale: int, edge_factor: int, slice_: int, slices: int):
        import hashlib

        for e in range(slice_, (1 << scale) * edge_factor, slices):
            s = t = 0
            for level in range(scale):
                u = int(hashlib.md5(f"{e}:{level}".encode()).hexdigest()[:7], 16) / 268435456
                s |= (u >= 0.76) << level
                t |= (0.57 <= u < 0.76 or u >= 0.95) << level
            yield s, t


@F.udtf
class CacheReplay:
    """cache_replay(TABLE(trace), capacity_bytes, score): the replay of one part, partitioned by part and ordered by seq."""

    def __init__(self):
        self.cache = None

    @staticmethod
    def analyze(table: AnalyzeArgument, capacity: AnalyzeArgument, score: AnalyzeArgument) -> AnalyzeResult:
        schema = T.StructType().add("part", T.IntegerType()).add("seq", T.LongType()).add("outcome", T.StringType()).add("evicted", T.IntegerType())
        return AnalyzeResult(schema, partitionBy=[PartitioningColumn("part")], orderBy=[OrderingColumn("seq")])

    def eval(self, row, capacity: int, score: str):
        if self.cache is None:
            self.cache = ReadCache(CacheConfig(capacity, score=score))
        outcome, evicted = self.cache.read(row["dst"], row["adj_bytes"], float(row["deg"]))
        yield row["part"], row["seq"], outcome, evicted


def register(spark: SparkSession) -> None:
    spark.udf.register("common_count", common_count)
    spark.udtf.register("rmat_edges", RmatEdges)
    spark.udtf.register("cache_replay", CacheReplay)
