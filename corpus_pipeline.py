"""A training-corpus pipeline: each stage reads what its predecessor kept and returns what it keeps itself.

STAGES lists (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame. All but the last return the columns
of ``docs``. ``run`` applies them to the documents table, writing and rereading what each stage kept.

Decisions go by row, not by doc_id. Defined results: a row without id is judged by its text like any other (and sorts last among its
copies); rows of one id are judged one by one, and repeated rows are copies, of which one stays; null and empty texts have no toxic
evidence, are of no language and so go in the second stage; empty tables give empty tables; other columns are passed on as they are.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from wedgework.llm import jaccard, langid, packing, toxicity
from wedgework.llm.common import discard, load, materialise, numbered, without

#: Words of a shingle and least similarity, in per cent, of near copies (op7_ngram_jaccard_join has a contract of its own).
SHINGLE, PERCENT = 5, 80


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    rows, key = numbered(docs)
    found = toxicity.detect(rows, load(spark, sf_dir, "labels"), carried=(key,))
    return without(rows, key, found.where("predicted = 1")).select(docs.columns)


def drop_unknown_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    rows, key = numbered(docs)
    return without(rows, key, langid.identify(rows, carried=(key,)).where("rejected")).select(docs.columns)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard.one_of_each(docs, k=SHINGLE, percent=PERCENT).select(docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("language_id", drop_unknown_language),
    ("ngram_jaccard_join", drop_copies),
    ("packing", pack),
]
#: Language models, shingle components and tokens can't be written in DuckDB SQL; tests compare with brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, older = load(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
        if older is not None:
            discard(older)
        older = docs
    return STAGES[-1][1](spark, docs, sf_dir)
