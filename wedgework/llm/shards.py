"""Sharding by extendible hashing.

A document's key is a 60-bit hash of its id. The directory starts as one bucket; a bucket that holds more bytes than the limit splits
on the next hash bit, others stay, so a shard is the shortest hash prefix whose documents fit. Byte totals come from distributed
sums at a few prefix depths; the driver sees only those sums (about four for each final shard), never documents.

Defined results: a null id hashes as the text 'null' and null text has 0 bytes; a bucket of one row isn't split, however large; rows
that repeat one id share all their bits and stay together (``oversized`` marks both cases); an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load

BITS = 60
#: Bytes of one shard in the registered query; a deployment passes its own.
LIMIT = 1 << 20


def key_hash():
    return F.conv(F.substring(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))), 1, 15), 16, 10).cast("long")


def hashed(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", key_hash().alias("h"), F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"))


def _sums(rows: DataFrame, depth: int) -> pd.DataFrame:
    found = rows.groupBy(F.shiftright("h", BITS - depth).alias("p")).agg(F.sum("n_bytes").alias("b"), F.count(F.lit(1)).alias("n"), (F.max("h") == F.min("h")).alias("same"))
    return pd.DataFrame([tuple(r) for r in found.collect()], columns=["p", "b", "n", "same"]).astype({"p": "int64", "b": "int64", "n": "int64", "same": bool})


def directory(rows: DataFrame, limit: int, first_depth: int = 8) -> pd.DataFrame:
    """Leaves as (start, depth, bytes, rows), sorted by start: together they cover the hash space."""
    leaves: list[tuple[int, int, int, int]] = []

    def settle(sums: pd.DataFrame, lo: int, hi: int) -> tuple[list[tuple[int, int]], int]:
        """Walk from depth lo to hi over the sums at hi; returns the prefixes that are still too large, and the largest."""
        at = {hi: sums.set_index("p")}
        for d in range(hi - 1, lo - 1, -1):
            below = at[d + 1]
            above = below.groupby(below.index.to_numpy() // 2)
            at[d] = above.agg({"b": "sum", "n": "sum", "same": "all"})
            at[d]["same"] &= above.size() == 1  # two halves with rows can't hold one hash
        large = list(at[lo].index)
        for d in range(lo, hi + 1):
            stay, rest = at[d].loc[at[d].index.intersection(large)], []
            for p, b, n, same in stay.itertuples():
                if b <= limit or n <= 1 or same or d == BITS:
                    leaves.append((p << (BITS - d), d, b, n))
                else:
                    rest.append(p)
            if d == hi:
                return rest, int(stay.loc[rest, "b"].max()) if rest else 0
            large = [q for p in rest for q in (2 * p, 2 * p + 1) if q in at[d + 1].index]
        return [], 0

    depth = first_depth
    rest, most = settle(_sums(rows, depth), 0, depth)
    while rest:
        more = min(BITS, depth + max(1, (most // limit).bit_length() + 1))
        inside = rows.join(F.broadcast(rows.sparkSession.createDataFrame([(int(p),) for p in rest], "q long")), F.shiftright("h", BITS - depth) == F.col("q"), "left_semi")
        rest, most = settle(_sums(inside, more), depth, more)
        depth = more
    return pd.DataFrame(sorted(leaves), columns=["start", "depth", "bytes", "rows"])


def _placer(spark: SparkSession, leaves: pd.DataFrame):
    """A function from a column of hashes to a struct of shard_id, local_depth and shard_bytes."""
    names = np.array([format(s >> (BITS - d), f"0{d}b") if d else "" for s, d in zip(leaves["start"], leaves["depth"], strict=True)], dtype=object)
    sent = spark.sparkContext.broadcast((leaves["start"].to_numpy(np.int64), leaves["depth"].to_numpy(np.int32), leaves["bytes"].to_numpy(np.int64), names))

    @F.pandas_udf("shard_id string, local_depth int, shard_bytes long")
    def look_up(h: pd.Series) -> pd.DataFrame:
        start, depth, size, name = sent.value
        i = np.searchsorted(start, h.to_numpy(), side="right") - 1
        return pd.DataFrame({"shard_id": name[i], "local_depth": depth[i], "shard_bytes": size[i]})

    return look_up


def assign(docs: DataFrame, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, shard_id (its hash prefix as bits; empty: the whole space), local_depth, shard_bytes, oversized."""
    rows = hashed(docs)
    placed = rows.withColumn("s", _placer(rows.sparkSession, directory(rows, limit))("h"))
    return placed.select("doc_id", "n_bytes", "s.shard_id", "s.local_depth", "s.shard_bytes", (F.col("s.shard_bytes") > limit).alias("oversized"))


def write_shards(docs: DataFrame, path: str, limit: int = LIMIT) -> DataFrame:
    """Write the documents as one folder for each shard; returns the assignment. Rows are placed by their own hash, so a null id is no matter."""
    rows = hashed(docs)
    look_up = _placer(rows.sparkSession, directory(rows, limit))
    docs.withColumn("shard_id", look_up(key_hash())["shard_id"]).repartition("shard_id").write.partitionBy("shard_id").parquet(path)
    return assign(docs, limit)


def op10_extendible_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign(load(spark, sf_dir, "documents"))


QUERIES = {"op10_extendible_sharding": op10_extendible_sharding}
SQL = {
    "op10_extendible_sharding": f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null')), 1, 15))::BIGINT AS h, coalesce(strlen(text), 0)::BIGINT AS n_bytes FROM documents),
ev AS (SELECT rid, doc_id, h, n_bytes, e.d AS depth, h >> ({BITS} - e.d) AS p FROM d, range(0, {BITS + 1}) AS e(d)),
s AS (SELECT *, sum(n_bytes) OVER (PARTITION BY depth, p) AS b, min(h) OVER (PARTITION BY depth, p) = max(h) OVER (PARTITION BY depth, p) AS same FROM ev),
leaf AS (SELECT * FROM s WHERE b <= {LIMIT} OR same QUALIFY row_number() OVER (PARTITION BY rid ORDER BY depth) = 1)
SELECT doc_id, n_bytes, CASE WHEN depth = 0 THEN '' ELSE lpad(bin(p), depth::INT, '0') END AS shard_id, depth::INT AS local_depth, b::BIGINT AS shard_bytes, b > {LIMIT} AS oversized FROM leaf"""
}
