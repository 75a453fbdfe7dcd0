"""Tables, edge lists, adjacency storage and result sinks."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: list[str] = []


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, which all executors share; a folder of our own only where that is unset (local tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or (_OWN[0] if _OWN else None)
    if not found:
        found = tempfile.mkdtemp(prefix="wedgework-")
        _OWN.append(found)
        atexit.register(shutil.rmtree, found, ignore_errors=True)
    return found.rstrip("/")


def settle(df: DataFrame, label: str) -> DataFrame:
    """Write into the shared folder and read back: stable rows for plans that use them twice, and a short lineage."""
    path = f"{shared_dir(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", sep: str = "\t", comment: str = "#") -> DataFrame:
    """src, dst from an edge list: csv or white-space text with comment lines, parquet or json with columns src and dst."""
    if fmt == "csv":
        return spark.read.csv(path, sep=sep, comment=comment, schema="src long, dst long").dropna()
    if fmt == "text":
        cut = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where(~F.trim("value").startswith(comment) & (F.trim("value") != ""))
        return lines.select(F.get(cut, 0).cast("long").alias("src"), F.get(cut, 1).cast("long").alias("dst"))
    return getattr(spark.read, fmt)(path).select(F.col("src").cast("long"), F.col("dst").cast("long"))


def write_adjacency(adj: DataFrame, path: str, table: str | None = None, buckets: int = 64) -> None:
    """Parquet sorted by vertex; as a table, bucketed by vertex, so that joins on it need no shuffle."""
    if table:
        adj.write.mode("overwrite").bucketBy(buckets, "v").sortBy("v").option("path", path).saveAsTable(table)
    else:
        adj.repartitionByRange("v").sortWithinPartitions("v").write.mode("overwrite").parquet(path)


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def write_scores(scores: DataFrame, path: str, fmt: str = "parquet", by: str | None = None) -> None:
    writer = scores.write.mode("overwrite").format(fmt)
    (writer.partitionBy(by) if by else writer).save(path)
