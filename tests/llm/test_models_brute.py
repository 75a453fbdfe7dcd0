"""Language identification and toxicity against the same definitions written out over strings."""

import math
import random
import zlib

import numpy as np
import pytest
from test_charlm import Brute, words_of

from wedgework.llm import langid, toxicity

SCHEMA = "doc_id long, text string, lang string, k int, score double"
EN = "the of and to in is that it was for on are with as be this have from light river".split()
DE = "der die und das ist nicht ein zu mit sich auf für den dem auch über schön fluss".split()


def fold(i):
    return None if i is None else zlib.crc32(str(i).encode()) % 5


def prose(rng, words, n):
    return " ".join(rng.choice(words) + rng.choice(("", "", ",", ".", "en", "ing")) for _ in range(n))


def test_language_against_brute_force(spark):
    rng = random.Random(21)
    rows = [(i, prose(rng, EN if i % 2 else DE, rng.randrange(5, 60)), "en" if i % 2 else "de") for i in range(90)]
    rows += [(90, "xq zzkw vjqx kkzq " * 6, None), (91, None, "en"), (92, "12 34", "de"), (None, prose(rng, DE, 9), "de"), (93, prose(rng, EN, 20), "de"), (7, rows[7][1], "en"), (94, "wszyscy ludzie rodzą się wolni i równi pod względem swej godności", None)]
    langs = ["de", "en"]
    taught = [(i, t, langs.index(g)) for i, t, g in rows if t is not None and g and fold(i) not in (None, 0, 4)]
    brute = Brute(taught, langid.ORDER, langid.ORDER, 2, False)
    want = []
    for i, t, g in rows:
        n = sum(len(w) + 1 for w in words_of(t))
        h = [-brute.log(t, k) / n for k in range(2)] if n else None
        want.append((i, t, g, "und" if h is None else langs[int(np.argmin(h))], min(h) if h else None, n))
    usual = {}
    for g in langs:
        own = [h for i, t, lang, p, h, _ in want if lang == g == p and t is not None and fold(i) == 4]
        usual[g] = (np.mean(own), np.std(own)) if own else None
    found = langid.identify(spark.createDataFrame([(i, t, g, 1, 0.0) for i, t, g in rows], SCHEMA).repartition(3)).collect()
    got = {(r.doc_id, r.n_letters, round(r.cross_entropy or 0, 5)): r for r in found}
    assert len(found) == len(rows)
    for i, _, _, p, h, n in want:
        r = got[i, n, round(h or 0, 5)]
        limit = None if p == "und" or usual[p] is None else usual[p][0] + langid.Z * (usual[p][1] + langid.SHORT / math.sqrt(n))
        assert (r.lang_pred, r.held_out, r.rejected) == (p, fold(i) == 0, p == "und" or limit is not None and h > limit)


def test_rejection_rates(spark):
    """Text of other languages and letter soup goes, ordinary rows that no model has seen stay."""
    rng = random.Random(22)
    rows = [(i, prose(rng, EN if i % 2 else DE, rng.randrange(20, 80)), "en" if i % 2 else "de") for i in range(300)]
    soup = lambda: " ".join("".join(rng.choice("bcdfghjklmnpqrstvwxz") for _ in range(rng.randrange(2, 9))) for _ in range(30))
    rows += [(1000 + i, soup(), None) for i in range(40)]
    found = langid.identify(spark.createDataFrame([(i, t, g, 1, 0.0) for i, t, g in rows], SCHEMA)).collect()
    assert sum(r.rejected for r in found if r.doc_id < 1000) == 0 and sum(r.rejected for r in found if r.doc_id >= 1000) == 40


def test_toxicity_against_brute_force(spark):
    rng = random.Random(23)
    bad = ["grumbol", "snarkel", "vextus"]
    rows = [(i, prose(rng, EN, rng.randrange(5, 70)) + (f" {rng.choice(bad)} {rng.choice(bad)}" if i % 3 == 0 else "")) for i in range(120)]
    rows += [(200, None), (201, ""), (None, "grumbol the of"), (3, "again the of and"), (202, "12 !!")]
    toxic = {i: int(i % 3 == 0) for i in range(110)} | {3: 1}
    docs = spark.createDataFrame([(i, t, "en", 1, 0.0) for i, t in rows], SCHEMA).repartition(3)
    labels = spark.createDataFrame([(i, x) for i, x in toxic.items()] + [(3, 0), (None, 1), (999, 1), (5, None)], "doc_id long, toxic int")
    brute = Brute([(i, t, toxic[i]) for i, t in rows if t is not None and i in toxic and fold(i) in (1, 2, 3)], toxicity.ORDER, toxicity.FREE, 2, True)

    def features(t):
        pieces = [(brute.log(p, 1) - brute.log(p, 0), sum(len(w) + 1 for w in words_of(p))) for p in (t or "").split()]
        n = sum(c for _, c in pieces)
        if not n:
            return [0.0] * 5
        top = sorted((max(0.0, min(d, toxicity.CLIP)) for d, _ in pieces), reverse=True) + [0.0] * 3
        return [sum(d for d, _ in pieces) / n, *top[:3], math.log1p(len(pieces))]

    found = toxicity.detect(docs, labels).collect()
    assert len(found) == len(rows)
    want = {(i, t): features(t) for i, t in rows}
    by_id = {}
    for (i, _), f in want.items():
        by_id.setdefault(i, []).append(f)
    for r in found:
        assert any([r[f] for f in toxicity.FEATURES] == pytest.approx(f, rel=1e-4, abs=1e-4) for f in by_id[r.doc_id])
        assert r.held_out == (fold(r.doc_id) == 0) and r.predicted == int(r.score >= 0.5) and 0 <= r.score <= 1
    # the scores are those of the logistic function whose gradient on the fold for fitting vanishes
    own = [(f, toxic[i]) for i, fs in by_id.items() if i in toxic and fold(i) == 4 for f in fs]
    x, y = np.array([f for f, _ in own]), np.array([k for _, k in own], dtype=float)
    scale = np.maximum(x.std(axis=0), 1e-9)
    logit = {r.doc_id: math.log(r.score / (1 - r.score)) for r in found if 1e-12 < r.score < 1 - 1e-12}
    some = [i for i in logit if i is not None and len(by_id[i]) == 1]
    a = np.concatenate([np.array([by_id[i][0] for i in some]) / scale, np.ones((len(some), 1))], axis=1)
    w = np.linalg.lstsq(a, np.array([logit[i] for i in some]), rcond=None)[0]
    z = np.concatenate([x / scale, np.ones((len(x), 1))], axis=1)
    gradient = z.T @ (1 / (1 + np.exp(-z @ w)) - y) + np.append(np.full(5, 1e-2), 1e-6) * w
    assert np.abs(gradient).max() < 1e-2
