"""Language identification by interpolated Kneser-Ney character models, one for each language.

A text goes to the language of the lowest cross-entropy for each predicted character. Models learn from the rows that have a language and
aren't held out, but for a fourth of them (by hash of the id): on that fourth, which no model has seen, rejection is calibrated. A text whose
cross-entropy lies further above what its language shows there than ``Z`` deviations, with room for short texts, belongs to none.

Defined results: null texts and texts without a letter are ``und`` with score 0; equal cross-entropies go to the first language in
alphabetical order; repeated rows give repeated rows; a row without id teaches nothing; with no learnable row everything is ``und``; where
some language is only known from rows kept for calibration, all rows teach and calibrate; other columns are ignored unless carried.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .charlm import scored
from .common import held_out, load, materialise

ORDER = 5
#: Deviations above a language's usual cross-entropy that a text may have.
Z = 8.0
#: What a text of one letter may have above that, in nats; it falls with the root of the number of letters.
SHORT = 1.5
#: Characters of evidence at most behind ``score``; it would be 1.0 for nearly every long text otherwise.
EVIDENCE = 60
_RUNS = re.compile(r"[^\W\d_]+").findall
SCORED = "lang_pred string, score double, cross_entropy double, n_letters long"


def letters(piece: str) -> list[str]:
    """Lower-cased runs of letters."""
    low = piece.lower()
    if low.isalpha():
        return [low]
    return [w for r in _RUNS(low) for w in ([r] if r.isalpha() else "".join(c if c.isalpha() else " " for c in r).split())]


def score(docs: DataFrame, order: int = ORDER, carried: tuple[str, ...] = ()) -> DataFrame:
    """Models from the rows that teach, and every row under them; ``known`` is the language of a row for calibration."""
    fold = F.crc32(F.col("doc_id").cast("string")) % 5
    rows = docs.select("doc_id", *carried, "text", "lang", held_out().alias("held_out"), F.when((fold != 0) & F.col("lang").isNotNull() & F.col("text").isNotNull(), fold).alias("fold"))
    found = rows.where("fold IS NOT NULL").groupBy("lang").agg(F.count_if(F.col("fold") != 4).alias("teach")).collect()  # one row for each language
    langs = sorted(r.lang for r in found)
    all_teach = any(not r.teach for r in found)
    if not langs:
        return rows.select("doc_id", *carried, "held_out", F.lit(None).cast("string").alias("known"), F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"), F.lit(None).cast("double").alias("cross_entropy"), F.lit(0).cast("long").alias("n_letters"))
    teaches, tells = (F.col("fold").isNotNull(), F.col("fold").isNotNull()) if all_teach else (F.col("fold") != 4, F.col("fold") == 4)
    k = F.when(teaches, F.array_position(F.array(*map(F.lit, langs)), F.col("lang")) - 1).cast("int")
    rows = rows.select("doc_id", *carried, "text", "held_out", F.when(tells, F.col("lang")).alias("known"), k.alias("k"))

    def measure(texts: Iterator[np.ndarray]) -> pa.Table:
        pred, conf, ce, size = [], [], [], []
        for r in texts:
            sums = r.sum(axis=0, dtype=np.float64)
            n = sums[-1]
            if n <= 0:
                pred.append("und"), conf.append(0.0), ce.append(None), size.append(0)
                continue
            h = -sums[:-1] / n
            i = int(np.argmin(h))
            pred.append(langs[i])
            conf.append(float(1 / np.exp((h[i] - h) * min(n, EVIDENCE)).sum()))
            ce.append(float(h[i]))
            size.append(int(n))
        return pa.table({"lang_pred": pa.array(pred, pa.string()), "score": pa.array(conf, pa.float64()), "cross_entropy": pa.array(ce, pa.float64()), "n_letters": pa.array(size, pa.int64())})

    return scored(rows, ["doc_id", *carried, "held_out", "known"], order, order, len(langs), False, letters, measure, SCORED)


def identify(docs: DataFrame, order: int = ORDER, z: float = Z, carried: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, the carried columns, held_out, lang_pred, score, cross_entropy, n_letters, rejected."""
    found = materialise(score(docs, order, carried), "languages")
    usual = (
        found.where(F.col("known") == F.col("lang_pred"))
        .groupBy(F.col("known").alias("own"))
        .agg(F.avg("cross_entropy").alias("mean"), F.coalesce(F.stddev_pop("cross_entropy"), F.lit(0.0)).alias("sd"))
    )
    limit = F.col("mean") + F.lit(z) * (F.col("sd") + F.lit(SHORT) / F.sqrt(F.greatest("n_letters", F.lit(1))))
    # one row for each language
    return found.join(F.broadcast(usual), F.col("own") == F.col("lang_pred"), "left").select(
        "doc_id", *carried, "held_out", "lang_pred", "score", "cross_entropy", "n_letters", ((F.col("lang_pred") == "und") | F.coalesce(F.col("cross_entropy") > limit, F.lit(False))).alias("rejected")
    )


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(load(spark, sf_dir, "documents"))


QUERIES = {"op2_language_id": op2_language_id}
SQL: dict[str, str] = {}
