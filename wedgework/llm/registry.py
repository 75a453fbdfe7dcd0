"""Queries and oracle SQL of the training-data operators."""

from . import bpe, htmltext, jaccard, langid, licenses, packing, quality, shards, simhash, toxicity

MODULES = (quality, langid, bpe, packing, jaccard, toxicity, htmltext, simhash, licenses, shards)
QUERIES = {k: f for m in MODULES for k, f in m.QUERIES.items()}
SQL = {k: s for m in MODULES for k, s in m.SQL.items()}
