"""Toxicity by class-conditional Kneser-Ney models with shared back-off.

Two character models, of toxic and of ordinary rows, share their lower orders, so that a rare expression counts only as far as one class
really prefers it. A text is compared by the length-normalised difference of its log likelihoods and by the differences of its three
strongest words, so that a few toxic words in a long text aren't averaged away. A logistic function, fitted on
labelled rows that neither the models nor the held-out set use, turns these into a score.

Defined results: a null text is empty; an empty text gets the score of a text without any evidence; of several labels of one id the
largest holds; label rows without a document, and null labels, teach nothing; with labels of one class only every score is that class's
share; where the rows kept for the logistic function have one class only, it is fitted on all labelled rows that aren't held out; repeated rows give repeated rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .charlm import classes_of, scored
from .common import load, materialise
from .langid import letters

#: Characters of word-initial grams, which are the classes' own, and of the shared grams inside words.
ORDER = 9
FREE = 5
#: Labelled rows to learn from at most; beyond it, an even share by hash of the id. Bounds what is broadcast to 18 bytes a row.
MOST_LABELS = 2_000_000
FEATURES = ("whole", "top1", "top2", "top3", "log_words")
#: Difference of log likelihoods of one word that counts at most.
CLIP = 15.0


def labelled(labels: DataFrame, most: int = MOST_LABELS) -> pd.DataFrame:
    """doc_id, toxic, fold (crc32 of the id as text, modulo 5; 0 is held out), sorted by id; at most about ``most`` rows."""
    rows = labels.where("doc_id IS NOT NULL AND toxic IS NOT NULL").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic")).withColumn("fold", (F.crc32(F.col("doc_id").cast("string")) % 5).cast("int")).where("fold != 0")
    n = rows.count()
    if n > most:
        rows = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(-(-n // most))) == 0)
    return rows.toArrow().to_pandas().sort_values("doc_id", ignore_index=True)


def send(docs: DataFrame, known: pd.DataFrame, folds: tuple[int, ...]):
    """Broadcast (sorted ids, labels) of the labelled rows of these folds."""
    part = known[known["fold"].isin(folds)]
    return docs.sparkSession.sparkContext.broadcast((part["doc_id"].to_numpy(np.int64), part["toxic"].to_numpy(np.int64)))


def labelled_rows(found: DataFrame, known: pd.DataFrame, folds: tuple[int, ...]) -> pd.DataFrame:
    """k and FEATURES of the labelled rows of these folds; the bound of ``labelled`` holds for them, too."""
    sent = send(found, known, folds)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            k = classes_of(b["doc_id"], sent.value)
            yield b.assign(k=k)[k >= 0][["k", *FEATURES]]

    return found.select("doc_id", *FEATURES).where("doc_id IS NOT NULL").mapInPandas(run, "k long, " + ", ".join(f"{f} double" for f in FEATURES)).toArrow().to_pandas()


def evidence(docs: DataFrame, order: int, labels, carried: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, the carried columns, held_out and FEATURES of every whole text, under the models of the labelled ones."""

    def measure(texts: Iterator[np.ndarray]) -> pa.Table:
        out = []
        for r in texts:
            own = np.zeros(len(FEATURES))
            out.append(own)
            d, n = r[:, 1] - r[:, 0], r[:, 2]
            if not n.any():
                continue
            own[0] = d.sum(dtype=np.float64) / n.sum(dtype=np.float64)
            own[4] = np.log1p(len(d))
            top = np.partition(np.concatenate([d, np.zeros(3)]), -3)[-3:]
            own[3], own[2], own[1] = np.clip(np.sort(top), 0, CLIP)
        rows = np.array(out).reshape(-1, len(FEATURES))
        return pa.table({f: rows[:, j] for j, f in enumerate(FEATURES)})

    rows = docs.select("doc_id", *carried, "text", F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False)).alias("held_out"))
    return scored(rows, ["doc_id", *carried, "held_out"], order, FREE, 2, True, letters, measure, ", ".join(f"{f} double" for f in FEATURES), labels)


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 50) -> np.ndarray:
    """Weights (the last is the constant) by Newton steps; both classes weigh as they occur."""
    x = np.concatenate([x, np.ones((len(x), 1))], axis=1)
    w, r = np.zeros(x.shape[1]), np.full(x.shape[1], ridge)
    r[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(r), x.T @ (p - y) + r * w)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


def detect(docs: DataFrame, labels: DataFrame, order: int = ORDER, carried: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, the carried columns, held_out, score, predicted and the evidence."""
    known = labelled(labels)
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))

    def constant() -> DataFrame:
        share = float(known["toxic"].mean()) if len(known) else 0.0
        return docs.select("doc_id", *carried, held.alias("held_out"), F.lit(share).alias("score"), F.lit(int(share >= 0.5)).alias("predicted"), *(F.lit(0.0).alias(f) for f in FEATURES))

    if known["toxic"].nunique() < 2:
        return constant()
    found = materialise(evidence(docs, order, send(docs, known, (1, 2, 3)), carried), "toxicity")
    fitted = labelled_rows(found, known, (4,))
    if fitted["k"].nunique() < 2:
        fitted = labelled_rows(found, known, (1, 2, 3, 4))
    if fitted["k"].nunique() < 2:  # the labels are of other documents
        return constant()
    x = fitted[list(FEATURES)].to_numpy(float)
    scale = np.maximum(x.std(axis=0), 1e-9)
    w = logistic(x / scale, fitted["k"].to_numpy(float))
    logit = F.lit(float(w[-1]))
    for f, v in zip(FEATURES, w[:-1] / scale, strict=True):
        logit = logit + F.lit(float(v)) * F.col(f)
    return found.withColumn("score", F.lit(1.0) / (F.lit(1.0) + F.exp(-logit))).select("doc_id", *carried, "held_out", "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), *FEATURES)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


QUERIES = {"op9_toxicity": op9_toxicity}
SQL: dict[str, str] = {}
