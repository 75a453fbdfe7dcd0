"""Helpers that the training-data operators share."""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Characters that separate words: space and \x09-\x0D.
WORD_SPACE = "\t\n\x0b\x0c\r "
_OWN: list[str] = []


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the test-data layout, by a path that only Spark needs to read."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or (where unset, as in local tests) one of our own."""
    found = spark.conf.get("spark.checkpoint.dir", None) or (_OWN[0] if _OWN else None)
    if not found:
        found = tempfile.mkdtemp(prefix="wedgework-")
        _OWN.append(found)
        atexit.register(shutil.rmtree, found, ignore_errors=True)
    return found.rstrip("/")


def materialise(df: DataFrame, label: str, light: bool = False) -> DataFrame:
    """Write df into the shared folder and read it back: cuts the lineage and outlives lost executors.

    ``light`` is for frames of few bytes behind a shuffle (edges and labels of components, keys): they go into a sixteenth of the shuffle's files.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    if light:
        df = df.coalesce(max(1, int(spark.conf.get("spark.sql.shuffle.partitions")) // 16))
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Delete the files behind a materialised frame that no pending plan needs any more."""
    jvm = df.sparkSession._jvm
    conf = df.sparkSession._jsparkSession.sessionState().newHadoopConf()
    for parent in {name.rsplit("/", 1)[0] for name in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(parent)
        path.getFileSystem(conf).delete(path, True)


def numbered(docs: DataFrame) -> tuple[DataFrame, str]:
    """The rows with a number of their own that is the same in every reading, and that column's name.

    Rows that come straight from files are known by a hash of the file's path and their place in it, if no two files share the hash; others
    are written once with a number.
    """
    key = "row"
    while key in docs.columns:
        key += "_"
    if docs._jdf.queryExecution().analyzed().getClass().getSimpleName() == "LogicalRelation":
        place = F.col("_metadata.row_index")
        for seed in range(8):
            file = F.xxhash64(F.col("_metadata.file_path"), F.lit(seed)).bitwiseAND(F.lit(0x7FFFFFFF))
            one = docs.agg(F.countDistinct("_metadata.file_path").alias("files"), F.countDistinct(file).alias("hashes"), F.max(place).alias("last")).first()
            if one.files == one.hashes and (one.last or 0) < 1 << 32:
                return docs.select("*", F.shiftleft(file, 32).bitwiseOR(place).alias(key)), key
    return materialise(docs.withColumn(key, F.monotonically_increasing_id()), "numbered"), key


#: Keys (8 bytes each) that are broadcast at most; beyond it the anti join is left to Spark.
BROADCAST_ROWS = 4_000_000


def without(docs: DataFrame, key: str, gone: DataFrame) -> DataFrame:
    """The rows whose key isn't among ``gone`` (a column of that name)."""
    gone = materialise(gone.select(key), "gone", light=True)
    small = gone.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    return docs.join(F.broadcast(gone) if small else gone, key, "left_anti")


def held_out(doc_id="doc_id"):
    """True for the rows that no model learns from: crc32 of the id as text, modulo 5, is 0."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 5 == 0, F.lit(False))


def words_sql(text: str) -> str:
    """SQL for the array of maximal runs of non-space characters of a string expression (no words: empty array)."""
    space = "' \\t\\n\\u000b\\u000c\\r'"
    trimmed = f"trim(BOTH {space} FROM {text})"
    return f"filter(split({trimmed}, '[ \\\\t\\\\n\\\\x0B\\\\f\\\\r]+'), x -> x != '')"


def release() -> None:
    """Give memory that a worker's last batch needed back to the machine: Python workers are reused and would keep it."""
    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another libc
        pass
