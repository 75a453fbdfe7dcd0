"""SimHash fingerprints and the search for all fingerprints within a Hamming radius.

Terms are shingles of five words (fewer words: the whole sequence); every occurrence votes, so a term weighs as often as it occurs.
Votes are counted two bits at a time: lane i of a term's 64-bit hash is ``(hash >>> i) & 0x100000001``, whose sum holds the counts
of bits i and i + 32 in its two halves. Thus 32 plain sums replace 64, all inside generated code, and a document's terms meet in
the map-side aggregate, so that only one row for each text is shuffled.

Defined results: null text is empty and an empty text has fingerprint zero; repeated rows give repeated rows; a null id
sorts below all others; where one id has several texts, the smallest prefix and fingerprint stand for "the next document".
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import load, materialise, words_sql

SHINGLE = 5
LOWEST = -(1 << 63)


def term_hashes_sql(text: str, k: int = SHINGLE) -> str:
    """SQL for the array of 64-bit term hashes of a string expression, one for each occurrence."""
    window = ", ".join(f"w[i + {j}]" if j else "w[i]" for j in range(k))
    return (
        f"transform(array({words_sql(text)}), w -> CASE WHEN size(w) = 0 THEN array() WHEN size(w) < {k} THEN array(xxhash64(array_join(w, ' '))) "
        f"ELSE transform(sequence(0, size(w) - {k}), i -> xxhash64({window})) END)[0]"
    )


def fingerprints(texts: DataFrame, keys: list[str], text: str = "body", weight: str | None = None) -> DataFrame:
    """keys, ``fp`` (long) and ``copies`` (rows that have them) for each distinct key. ``weight`` is a column with an integer weight of all terms of a text."""
    votes = [F.expr(f"shiftrightunsigned(h, {i}) & 4294967297L") for i in range(32)]
    one = F.when(F.col("h").isNotNull(), F.lit(1))
    if weight:
        votes, one = [v * F.col(weight) for v in votes], F.when(F.col("h").isNotNull(), F.col(weight))
    terms = texts.select(*keys, *([weight] if weight else []), F.explode(F.concat(F.array(F.lit(None).cast("long")), F.expr(term_hashes_sql(text)))).alias("h"))  # the null tells the rows apart from their terms
    counted = terms.groupBy(*keys).agg(F.count_if(F.col("h").isNull()).alias("copies"), F.sum(one).alias("n"), *(F.sum(v).alias(f"s{i}") for i, v in enumerate(votes)))
    bits = [f"shiftleft(bigint(2 * (s{i} & 4294967295L) > n), {i})" for i in range(32)] + [f"shiftleft(bigint(2 * shiftrightunsigned(s{i}, 32) > n), {i + 32})" for i in range(32)]
    return counted.select(*keys, F.expr(f"coalesce({' | '.join(bits)}, 0L)").alias("fp"), "copies")


def likeness(a, b):
    """Share of equal bits."""
    return F.lit(1.0) - F.bit_count(F.col(a).bitwiseXOR(F.col(b))) / F.lit(64.0)


def as_text(fp: str):
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def next_ids(ids: DataFrame, rows_a_bucket: int = 20_000, most_buckets: int = 4096) -> DataFrame:
    """k -> nk, the next id in descending order (after the last: the first), for a column k of ids.

    Ids fall into ordered buckets between approximate quantiles; the order within a bucket is a window over that bucket, and the
    step from one bucket to the next needs one row for each bucket (at most ``most_buckets`` reach the driver).
    """
    ids = ids.select("k").distinct()
    n = ids.count()
    if not n:
        return ids.withColumn("nk", F.col("k"))
    steps = min(most_buckets, -(-n // rows_a_bucket))
    cuts = ids.agg(F.percentile_approx("k", [i / steps for i in range(1, steps)] or [0.5], 100 * steps)).first()[0] if steps > 1 else []
    cuts = sorted(set(cuts))
    depth = max(1, len(cuts).bit_length())
    known = f"array({', '.join(f'{c}L' if c > LOWEST else 'bigint(-9223372036854775808)' for c in cuts)})" if cuts else "array(0L)"
    # binary search for the number of cuts below or at k
    found = (
        f"aggregate(transform(sequence({depth - 1}, 0, -1), e -> int(shiftleft(1, e))), 0, (lo, s) -> CASE WHEN lo + s <= {len(cuts)} AND cuts[least(lo + s, {max(len(cuts), 1)}) - 1] <= k THEN lo + s ELSE lo END)"
        if cuts
        else "0"
    )
    placed = ids.withColumn("cuts", F.expr(known)).select("k", F.expr(found).alias("b"))
    edges = {r.b: r.top for r in placed.groupBy("b").agg(F.max("k").alias("top")).collect()}
    below, order = {}, sorted(edges)
    for i, b in enumerate(order):
        below[b] = edges[order[i - 1]]  # the lowest bucket wraps to the highest
    lit = F.create_map(*(F.lit(x) for b in order for x in (b, below[b])))
    return placed.select("k", F.coalesce(F.lead("k").over(W.partitionBy("b").orderBy(F.desc("k"))), lit[F.col("b")]).alias("nk"))


def edited_pairs(docs: DataFrame) -> DataFrame:
    """Each document with its edited text. Whole texts are shuffled once (both joins read the same exchange); only prefixes move a second time."""
    base = docs.select(F.coalesce("doc_id", F.lit(LOWEST)).alias("k"), F.coalesce("text", F.lit("")).alias("body"))
    sizes = base.select("k", F.length("body").cast("long").alias("n")).distinct()
    asked = sizes.join(next_ids(base), "k").select(F.col("k").alias("of"), "nk", "n")
    given = (
        asked.join(base, F.col("nk") == F.col("k"))
        .select("of", "nk", "n", F.expr("substring(body, 1, int(n div 3))").alias("piece"))
        .groupBy("of", "nk", "n")
        .agg(F.min("piece").alias("piece"))
    )
    # the two bounds say that the sizes are equal, but leave k alone as the key by which both sides are dealt
    n = F.length("body").cast("long")
    return base.join(given, (F.col("k") == F.col("of")) & (n <= F.col("n")) & (n >= F.col("n"))).select(
        F.when(F.col("k") != LOWEST, F.col("k")).alias("doc_id"), "k", "nk", F.col("n").alias("n_chars"), "body", F.expr("concat(substring(body, 1, int(n - n div 3)), piece)").alias("edited")
    )


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = edited_pairs(load(spark, sf_dir, "documents"))
    keyed = pairs.select("doc_id", "k", "nk", "n_chars", F.xxhash64("body").alias("bh"), F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), "body", "edited")
    keys = ["doc_id", "k", "nk", "n_chars", "bh", "edited_sha256"]
    both = keyed.select(*keys, F.explode(F.array(F.struct(F.lit(0).alias("which"), F.col("body")), F.struct(F.lit(1).alias("which"), F.col("edited").alias("body")))).alias("t"))
    fps = fingerprints(both.select(*keys, "t.which", "t.body"), [*keys, "which"])
    own = fps.groupBy(*keys).agg(F.max(F.when(F.col("which") == 0, F.col("fp"))).alias("fp"), F.max(F.when(F.col("which") == 1, F.col("fp"))).alias("edited_fp"), F.max("copies").alias("copies"))
    own = materialise(own, "fingerprints")  # read twice below; the texts are not
    nexts = own.groupBy(F.col("k").alias("nk")).agg(F.min("fp").alias("next_fp"))
    each = own.join(nexts, "nk").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies"))))
    return each.select(
        "doc_id", "n_chars", "edited_sha256", as_text("fp").alias("fingerprint"), as_text("edited_fp").alias("edited_fingerprint"),
        likeness("fp", "edited_fp").alias("near_edited"), likeness("fp", "next_fp").alias("near_next"),
    )


def within(fps: DataFrame, queries: DataFrame, radius: int = 3, blocks: int = 6) -> DataFrame:
    """All pairs (query_fp, fp) of distinct fingerprints at most ``radius`` bits apart.

    64 bits fall into ``blocks`` blocks; two fingerprints that differ in at most ``radius`` bits agree on some ``blocks - radius`` of
    them. One permuted table for each such choice; its key is the chosen bits. Equal fingerprints are met once (distinct first), so
    copies make no pairs.
    """
    edges = [64 * i // blocks for i in range(blocks + 1)]
    part = [sum(1 << b for b in range(edges[i], edges[i + 1])) for i in range(blocks)]
    masks = [sum(part[i] for i in chosen) for chosen in combinations(range(blocks), blocks - radius)]
    signed = [m - (1 << 64) if m >= 1 << 63 else m for m in masks]

    def tables(df: DataFrame, name: str) -> DataFrame:
        rows = F.array(*(F.struct(F.lit(t).alias("t"), F.col(name).bitwiseAND(F.lit(m)).alias("key")) for t, m in enumerate(signed)))
        return df.select(name).distinct().select(name, F.explode(rows).alias("r")).select(name, "r.t", "r.key")

    hits = tables(queries.select(F.col("fp").alias("query_fp")), "query_fp").join(tables(fps, "fp"), ["t", "key"])
    return hits.where(F.bit_count(F.col("query_fp").bitwiseXOR(F.col("fp"))) <= radius).select("query_fp", "fp").distinct()


def simhash_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents whose id is divisible by 20, against all: pairs of fingerprints within three bits, and the documents of these fingerprints.

    Rows of kind ``pair`` have query_fp and fp, rows of kind ``member`` have fp and doc_id; many copies of a document thus make no products.
    """
    docs = load(spark, sf_dir, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("body"))
    fps = materialise(fingerprints(docs.withColumn("bh", F.xxhash64("body")), ["doc_id", "bh"]), "fingerprints")
    pairs = materialise(within(fps, fps.where(F.col("doc_id") % 20 == 0)), "pairs")
    met = pairs.select(F.explode(F.array("query_fp", "fp")).alias("fp")).distinct()
    members = fps.select("fp", "doc_id").distinct().join(met, "fp", "left_semi")
    none = F.lit(None).cast("long")
    return pairs.select(F.lit("pair").alias("kind"), "query_fp", "fp", none.alias("doc_id")).unionByName(members.select(F.lit("member").alias("kind"), none.alias("query_fp"), "fp", "doc_id"))


QUERIES = {"op4_simhash": op4_simhash, "simhash_neighbours": simhash_neighbours}
SQL: dict[str, str] = {}
