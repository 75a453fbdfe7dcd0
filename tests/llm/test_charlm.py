"""The distributed character models against interpolated Kneser-Ney written out over strings."""

import math
import random
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest

from wedgework.llm import charlm, langid

SHAPES = [(False, 5, 5), (True, 9, 5), (False, 3, 3)]


def random_rows(n):
    rng = random.Random(12)
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randrange(1, 14)))
    rare = [word() for _ in range(n)]
    rows = [(i, " ".join(rare[i * 40 : i * 40 + 40] + ["The", "river-stone,", "12"]), i % 3 if i % 3 < 2 else None) for i in range(n // 40)]
    return rows + [(None, None, 0), (-1, "", 1), (-2, "x" * 200, None)]


def words_of(text):
    found = [w for p in (text or "").split() for w in langid.letters(p)]
    return [w[at : at + charlm.UNIT] for w in found for at in range(0, len(w), charlm.UNIT)]


class Brute:
    """Counts, continuation counts and discounts in dictionaries; the probability of a character by plain recursion."""

    def __init__(self, rows, order, free, classes, shared):
        self.order, self.free, self.classes = order, free, classes
        raw = defaultdict(lambda: [0] * classes)
        for _, t, k in rows:
            if k is None:
                continue
            for w in words_of(t):
                m = charlm.BEGIN + w + charlm.FINISH
                for j in range(1, len(m)):
                    for n in range(1, min(order, j + 1) + 1):
                        if n <= free or n == j + 1:
                            raw[m[j - n + 1 : j + 1]][k] += 1
        before = defaultdict(lambda: [0] * classes)
        for g, c in raw.items():
            if 1 < len(g) <= free:
                for k in range(classes):
                    before[g[1:]][k] += c[k] > 0
        self.c = {}
        for g, c in raw.items():
            first = g[0] == charlm.BEGIN
            own = c if first or len(g) >= free else before[g]
            self.c[g] = [sum(own)] * classes if shared and not first else list(own)
        self.letters = sum(len(g) == 1 for g in self.c) + 1
        self.total, self.kinds = Counter(), Counter()
        ones, twos = Counter(), Counter()
        for g, c in self.c.items():
            for k in range(classes):
                self.total[g[:-1], k] += c[k]
                self.kinds[g[:-1], k] += c[k] > 0
                ones[len(g), k] += c[k] == 1
                twos[len(g), k] += c[k] == 2
        self.d = {(n, k): min(max(ones[n, k] / (ones[n, k] + 2 * twos[n, k]) if ones[n, k] else 0.5, 0.1), 0.95) for n in range(1, order + 1) for k in range(classes)}

    def log(self, text, k):
        out = 0.0
        for w in words_of(text):
            m = charlm.BEGIN + w + charlm.FINISH
            for j in range(1, len(m)):
                p = 1 / self.letters
                for n in range(1, min(self.order, j + 1) + 1):  # each order interpolates with what the orders below gave
                    g = m[j - n + 1 : j + 1]
                    if not (n <= self.free or n == j + 1):
                        continue
                    total = self.total[g[:-1], k]
                    if total:
                        p = max(self.c.get(g, [0] * self.classes)[k] - self.d[n, k], 0) / total + self.d[n, k] * self.kinds[g[:-1], k] / total * p
                out += math.log(p)
        return out


@pytest.mark.parametrize("far", [False, True])
@pytest.mark.parametrize("shared,order,free", SHAPES)
def test_against_brute_force(spark, monkeypatch, shared, order, free, far):
    if far:  # the way of models that are too large to send
        monkeypatch.setattr(charlm, "MODEL_BYTES", 0)
        monkeypatch.setattr(charlm, "CHUNK", 5000)
        monkeypatch.setattr(charlm, "BATCH", 900)
    else:
        monkeypatch.setattr(charlm, "REMEMBERED", 1500)
    monkeypatch.setattr(charlm, "SLICE", 700)
    rows = random_rows(2400)
    df = spark.createDataFrame(rows, "doc_id long, text string, k int").repartition(3)
    measure = lambda texts: (lambda r: pa.table({"a": r[:, 0], "b": r[:, 1], "n": r[:, 2]}))(np.array([x.sum(axis=0, dtype=np.float64) for x in texts]).reshape(-1, 3))
    got = {r.doc_id: r for r in charlm.scored(df, ["doc_id"], order, free, 2, shared, langid.letters, measure, "a double, b double, n double").collect()}
    assert len(got) == len(rows)
    brute = Brute(rows, order, free, 2, shared)
    for i, t, _ in rows:
        assert got[i].n == sum(len(w) + 1 for w in words_of(t))
        assert [got[i].a, got[i].b] == pytest.approx([brute.log(t, 0), brute.log(t, 1)], rel=1e-6, abs=1e-6), i


def test_no_gram_is_left_out(spark):
    """More distinct grams than the 800 000 that the models were once cut to: all are in the table."""
    rng = random.Random(13)
    words = {"".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(9)) for _ in range(60_000)}
    names = sorted(words)
    df = spark.createDataFrame([(i, " ".join(names[i::50]), i % 2) for i in range(50)], "doc_id long, text string, k int").repartition(4)
    table, orders = charlm.gram_table(charlm.count_grams(df, 9, 5, langid.letters), 9, 5, 2, True)
    marked = [charlm.BEGIN + w + charlm.FINISH for w in words]
    want = {m[j - n + 1 : j + 1] for m in marked for j in range(1, len(m)) for n in range(1, 10) if (n <= min(5, j + 1)) or n == j + 1}
    assert len(want) > 800_000
    assert sum(rows - 1 for rows, *_ in orders) == len(want)
    assert table.where("c0 + c1 > 0").count() == len(want)
