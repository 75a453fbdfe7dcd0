"""The ten operators on small tables with nulls, empty and long texts, ties, repeated rows and clashing columns, against brute force."""

import hashlib
import random
import re
import zlib
from collections import Counter
from itertools import combinations

import numpy as np
import pytest

from wedgework.llm import bpe, htmltext, jaccard, langid, licenses, packing, quality, shards, simhash, toxicity

WORDS = re.compile(r"[^\x20\x09-\x0D]+").findall
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, cls long, k int, h long, score double"


def table(spark, rows):
    return spark.createDataFrame([(i, t, g, "s", None if t is None else len(t), 7, 7, 7, 7.0) for i, t, g in rows], SCHEMA)


def prose(rng, n, words="the of and river stone walks slowly under bright morning light while seven birds sing above old houses".split()):
    return " ".join(rng.choice(words) + (str(rng.randrange(40)) if rng.random() < 0.5 else "") for _ in range(n))


@pytest.fixture(scope="module")
def texts():
    rng = random.Random(3)
    base = [prose(rng, rng.randrange(60, 120)) for _ in range(12)]
    near = []
    for t in base[:4]:
        w = t.split()
        near.append(" ".join(w[:-2] + ["changed", "ending"]))
        near.append(" ".join(["new"] + w))
    odd = [None, "", " ", "\n\t \n", "one", "two words", "a b c d e", "Ünïcode straße 東京 🙂", "x" * 5000, "a\nb\na\nb\n", "same same same same same same", "tail f", "long " + prose(rng, 3000), "UPPER lower Upper", "upper LOWER uPPER"]
    return base + near + base[:2] + odd


@pytest.fixture(scope="module")
def docs(spark, texts):
    rows = [(3 * i, t, "en") for i, t in enumerate(texts)] + [(None, "a document without an id", None), (3, texts[1], "en")]
    return table(spark, rows).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return table(spark, [(0, "x", "en")]).limit(0)


def test_quality_measures(docs, texts):
    got = {r.doc_id: r for r in quality.apply_policy(quality.ledger(docs), quality.STRICT).collect()}
    for i, t in enumerate(texts):
        w = WORDS(t or "")
        grams = [tuple(w[j : j + 3]) for j in range(len(w) - 2)]
        twice = {g for g in grams if grams.count(g) > 1} if len(grams) < 500 else {g for g, c in __import__("collections").Counter(grams).items() if c > 1}
        covered = {j + d for j, g in enumerate(grams) if g in twice for d in range(3)}
        lines = [x for x in (t or "").split("\n") if WORDS(x)]
        r = got[3 * i]
        assert (r.n_words, r.word_chars, r.n_repeat_words, r.n_dup_lines) == (len(w), sum(map(len, w)), len(covered), len(lines) - len(set(lines))), t
        assert r.n_symbols == len(re.findall(r"[#*$%&|<>]", t or ""))
        assert (r.fail_bits & 1 > 0) == (len(w) < 50)
    assert quality.ledger(docs).count() == docs.count()


def test_ablations(docs, empty):
    book = quality.ledger(docs).collect()
    for r in quality.ablations(quality.ledger(docs), quality.STRICT).collect():
        one = 1 << next(x.bit for x in quality.RULES if x.name == r.rule)
        assert r.n_failed == sum(b.fail_bits & one > 0 for b in book)
        assert r.n_failed_alone == sum(b.fail_bits == one for b in book)
        assert r.n_kept_without == sum(b.fail_bits & ~one == 0 for b in book)
    assert quality.ledger(empty).count() == 0
    assert {r.n_failed for r in quality.ablations(quality.ledger(empty), quality.STRICT).collect()} == {0}


def test_language(spark, empty):
    rng = random.Random(1)
    en = "the of and to in is that it was for on are with as be this have from".split()
    de = "der die und das ist nicht ein zu mit sich auf für den dem auch über schön".split()
    rows = [(i, " ".join(rng.choice(en if i % 2 else de) for _ in range(40)), "en" if i % 2 else "de") for i in range(80)]
    rows += [(1000, None, "en"), (1001, "", "en"), (1002, "12 34 -- !!", "de"), (1003, "the of and to", None), (None, "der die und das", None), (1005, "xqzjk wvvxq kjzzq qqxj zzkw vjqx kkzq jxwv qzvk xxjq " * 8, None), (1003, "the of and to", None)]
    got = {}
    found = langid.identify(table(spark, rows)).collect()
    assert len(found) == len(rows)
    for r in found:
        got[r.doc_id] = r
    assert all(got[i].lang_pred == ("en" if i % 2 else "de") for i in range(80))
    assert all(got[i].held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i in range(80))
    assert {got[i].lang_pred for i in (1000, 1001, 1002)} == {"und"} and all(got[i].rejected and got[i].score == 0 for i in (1000, 1001, 1002))
    assert got[1003].lang_pred == "en" and got[None].lang_pred == "de" and not got[1003].rejected
    assert got[1005].rejected and got[1005].cross_entropy > 2 * got[1].cross_entropy
    assert not any(got[i].rejected for i in range(80))
    assert langid.identify(empty).count() == 0
    assert {r.lang_pred for r in langid.identify(table(spark, [(1, "abc", None)])).collect()} == {"und"}


def test_character_model_sums_to_one(spark):
    from wedgework.llm.charlm import BEGIN, FINISH, count_grams, fit, gram_table

    words = "banana bandana cabana ananas nab cab"
    for shared, order, free in ((False, 4, 4), (True, 6, 3)):
        rows = spark.createDataFrame([(words, 0), ("banana cab cab", 1)], "text string, k int")
        table, orders = gram_table(count_grams(rows, order, free, langid.letters), order, free, 2, shared)
        model = fit(table, orders, free)
        letters = sorted(set(words) - {" "}) + [FINISH, "q"]  # one letter that nobody has seen
        for context in ("", "b", "ban", "cabana", "nnn", "zz"):
            total = np.zeros(2)
            for c in letters:
                points = np.frombuffer((BEGIN + context + c).encode("utf-32-le"), dtype=np.uint32).astype(np.uint64)
                total = total + np.exp(model.positions(points, np.arange(len(points)))[-1])
            assert total == pytest.approx(1, abs=1e-6), (shared, context, total)


def test_bpe_against_the_library(spark, docs, empty):
    import public_tokenizers as tokenizers
    import tiktoken

    path = tokenizers.path("byte_bpe_multi_50k.tiktoken")
    ranks = bpe.read_ranks(path)
    library = tiktoken.Encoding("own", pat_str=tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    rng = random.Random(2)
    odd = ["".join(rng.choice("ab cd  \n\t'stréß中🙂\x1c\x85　 .,%12٣ªé'\r\x00") for _ in range(rng.randrange(50))) for _ in range(300)]
    own = bpe.Codec(path, tokenizers.PATTERN)
    for t, (ids, back) in zip(odd, own.encode(odd), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == library.encode_ordinary(t) and back == t.encode()
    words = [w.encode() for t in odd for w in t.split()] + [b"ab" * 700]
    assert [bpe.heap_encode(w, ranks) for w in words] == [np.frombuffer(i, "<u4").tolist() for i, _ in own.contract(words)]
    got = bpe.tokenise(docs, path, tokenizers.PATTERN, keep_ids=True).collect()
    want = {(r.doc_id, r.text) for r in docs.collect()}
    by = {}
    for i, t in want:
        by.setdefault(i, []).append(t)
    for r in got:
        t = by[r.doc_id][0] or ""
        ids = library.encode_ordinary(t)
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest() and r.decoded_sha256 == hashlib.sha256(t.encode()).hexdigest()
    rows = spark.createDataFrame([(r.doc_id, bytes(r.ids)) for r in got], "doc_id long, ids binary")
    assert all(bytes(r.decoded).decode() == (by[r.doc_id][0] or "") for r in bpe.decode_ids(rows, path, tokenizers.PATTERN).collect())
    assert bpe.tokenise(empty, path, tokenizers.PATTERN).count() == 0


def test_bpe_work_is_not_repeated(monkeypatch):
    """Pieces of a group are split together; words in use survive the cache's overflow and are contracted once."""
    import public_tokenizers as tokenizers
    import tiktoken

    path = tokenizers.path("byte_bpe_multi_50k.tiktoken")
    library = tiktoken.Encoding("own", pat_str=tokenizers.PATTERN, mergeable_ranks=bpe.read_ranks(path), special_tokens={})
    own, asked, splits = bpe.Codec(path, tokenizers.PATTERN), Counter(), []

    class Ranks(dict):
        def get(self, key, default=None):
            asked[key] += 1
            return super().get(key, default)

    own.ranks, split = Ranks(own.ranks), own.split
    own.split = lambda text: splits.append(text) or split(text)
    monkeypatch.setattr(bpe, "CACHE", 2000)
    rng = random.Random(4)
    words = sorted({"".join(rng.choices(["tion", "heit", "ción", "qu", "x", "os"], k=5)) for _ in range(30_000)})[:6500]
    rng.shuffle(words)
    common = words[:500]
    for k in range(6):
        text = " " + " ".join([*common, *words[500 + 1000 * k : 1500 + 1000 * k]])
        [(ids, back)] = own.encode([text])
        assert np.frombuffer(ids, "<u4").tolist() == library.encode_ordinary(text) and back == text.encode()
    assert len(words) == 6500 and len(splits) <= 12
    assert {asked[(" " + w).encode()] for w in words} == {1}
    assert list(own.encode([])) == [] and list(own.encode([""])) == [(b"", b"")]


def _simhash(t):
    import xxhash

    w = WORDS(t)
    if not w:
        return 0
    if len(w) < 5:
        hs = [xxhash.xxh64_intdigest(" ".join(w).encode(), 42)]
    else:
        hs = []
        for i in range(len(w) - 4):
            s = 42
            for x in w[i : i + 5]:
                s = xxhash.xxh64_intdigest(x.encode(), s)
            hs.append(s)
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def test_simhash_against_brute_force(spark, docs, texts, empty, monkeypatch):
    monkeypatch.setattr(simhash, "load", lambda s, d, n: docs)
    got = {r.doc_id: r for r in simhash.op4_simhash(spark, "").collect()}
    rows = {3 * i: t or "" for i, t in enumerate(texts)}
    order = sorted(rows, reverse=True)
    for i in order:
        after = order[order.index(i) + 1] if i else None
        t = rows[i]
        other = rows[after] if after is not None else "a document without an id"
        edited = t[: len(t) - len(t) // 3] + other[: len(t) // 3]
        a, b, c = _simhash(t), _simhash(edited), _simhash(other)
        assert (got[i].fingerprint, got[i].edited_fingerprint, got[i].n_chars) == (f"{a:016x}", f"{b:016x}", len(t)), i
        assert got[i].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert got[i].near_edited == 1 - (a ^ b).bit_count() / 64 and got[i].near_next == 1 - (a ^ c).bit_count() / 64
    assert simhash.op4_simhash(spark, "").count() == docs.count()
    monkeypatch.setattr(simhash, "load", lambda s, d, n: empty)
    assert simhash.op4_simhash(spark, "").count() == 0


def test_next_ids_over_buckets(spark):
    ids = spark.range(0, 900, 3).selectExpr("id * id - 50 AS k")
    want = sorted((r.k for r in ids.collect()), reverse=True)
    got = {r.k: r.nk for r in simhash.next_ids(ids, rows_a_bucket=16).collect()}
    assert got == dict(zip(want, want[1:] + want[:1], strict=True))


def test_radius_search(spark):
    rng = random.Random(4)
    base = [rng.getrandbits(64) for _ in range(40)]
    fps = base + [b ^ sum(1 << x for x in rng.sample(range(64), rng.randrange(1, 6))) for b in base for _ in range(3)]
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    df = spark.createDataFrame([(f,) for f in signed], "fp long")
    for radius, blocks in ((1, 4), (3, 6)):
        want = {(a, b) for a in set(signed) for b in set(signed) if ((a ^ b) & (1 << 64) - 1).bit_count() <= radius}
        assert {tuple(r) for r in simhash.within(df, df, radius, blocks).collect()} == want


def test_licenses(spark, empty):
    long = licenses.TEMPLATES[2][1]
    rows = [
        (0, None), (1, ""), (2, "Some prose.\nReleased under the MIT License.\nMore prose."), (3, "Text. Licensed under the Apache License, Version 2.0. Text goes on here."), (4, "licensed UNDER cc by-nc 4.0"),
        (5, "Copyright 2020 Somebody\n\n" + long), (6, "The license of a driver is not a licence under which we stand"), (7, "This work is licensed under the GNU General Public License, version 3."), (8, "License"), (8, "License"),
        (9, (long + "\n") * 3), (10, "Notes on seven birds.\nThis work is licensed under the GNU General\nPublic License, version 3. More notes follow here, and they go on for long."),
        (11, "Header\n\n" + long.replace("The above", "\n\nThe above").replace("THE SOFTWARE IS", "\n\nTHE SOFTWARE IS") + "\n\n" + "seven birds sing above old houses. " * 90),
        (12, "Old birds sing. " * 30 + " ".join(f"{x} " + "\n" * (i % 9 == 8) for i, x in enumerate(long.split())) + " Old birds sing." * 30), (13, "under the river by the work " * 200),
    ]
    got = [(r.doc_id, r.license, round(r.dice, 3)) for r in licenses.scan(table(spark, [(i, t, None) for i, t in rows])).collect()]
    assert len(got) == len(rows)
    by = {i: (n, d) for i, n, d in got}
    assert by[0] == by[1] == by[6] == by[8] == (None, 0.0)
    assert [by[i][0] for i in (2, 3, 4, 5, 7)] == ["MIT", "Apache-2.0", "CC-BY-NC-4.0", "MIT", "GPL-3.0"] and by[2][1] == by[4][1] == 1.0
    assert by[9][0] == "MIT" and by[9][1] > 0.98 and by[10] == ("GPL-3.0", 1.0) and by[11][0] == "MIT" and by[12][0] == "MIT" and by[13] == (None, 0.0)
    assert licenses.scan(empty).count() == 0


@pytest.mark.parametrize("n", [1, 7, 300])
def test_packing(spark, texts, n, empty):
    import public_tokenizers as tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(tokenizers.path("byte_bpe_50k.json"))
    rows = [(i, (texts[i % len(texts)] or "") * (1 + i % 3) or None, None) for i in range(n)]
    rows += [(n, "a <|endoftext|>b<|endoftext|><|endoftext|> c\n<|endoftext|>  <|endoftext| >", None), (n + 1, "<|endoftext|>", None)]
    got = packing.pack_documents(table(spark, rows).repartition(4)).collect()
    ids = {i: tok.encode(t or "", add_special_tokens=False).ids + [packing.END] for i, t, _ in rows}
    for i, want in ids.items():
        mine = sorted((r.start, r.length, r.ids_crc32, r.doc_tokens) for r in got if r.doc_id == i)
        assert [x for s, size, _, _ in mine for x in want[s : s + size]] == want and {x[3] for x in mine} == {len(want)}
        assert all(c == zlib.crc32(np.array(want[s : s + size], "<u4").tobytes()) for s, size, c, _ in mine)
    seqs = {}
    for r in got:
        seqs.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in seqs.values():
        at = 0
        for o, size in sorted(parts):
            assert o == at
            at += size
        assert at <= packing.WINDOW
    total = sum(map(len, ids.values()))
    assert len(seqs) <= total // packing.WINDOW + 1 + max(1, total // packing.WINDOW // 20)
    assert packing.pack_documents(empty).count() == 0


def test_packing_plan_on_large_and_hot_histograms():
    rng = np.random.default_rng(0)
    for counts in ({700: 10**9}, {2048: 5, 1: 10**6}, {int(n): int(c) for n, c in zip(rng.integers(1, 2049, 900), rng.integers(1, 10**7, 900), strict=True)}):
        plan = packing.make_plan(counts)
        for n, c in counts.items():
            ranks = np.unique(np.concatenate([[0, c - 1], rng.integers(0, c, 50)]))
            seq, _ = packing.place(plan, np.full(len(ranks), n), ranks)
            assert (seq >= 0).all()
    small = {1500: 3, 500: 4, 48: 5, 1000: 2}
    plan = packing.make_plan(small)
    n = np.repeat(list(small), list(small.values()))
    seq, slot = packing.place(plan, n, np.concatenate([np.arange(c) for c in small.values()]))
    assert np.bincount(seq, weights=n).max() <= 2048 and len(set(zip(seq.tolist(), slot.tolist(), strict=True))) == len(n)


def test_nnls_against_optimality():
    rng = np.random.default_rng(1)
    a, b = rng.random((12, 20)), rng.random(12) * 100
    x = packing.nnls(a, b)
    g = a.T @ (b - a @ x)
    assert (x >= 0).all() and (g < 0.05).all() and np.abs(g[x > 0]).max() < 1e-3


def brute_components(rows, percent=85):
    sets = {}
    for i, t in rows:
        w = WORDS(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[i] = {tuple(w[j : j + 4]) for j in range(len(w) - 3)} or ({tuple(w)} if w else set())
    up = {i: i for i in sets}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in combinations(sets, 2):
        if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
            x, y = sorted((root(a), root(b)))
            up[y] = x
    return {i: (i, len(s), root(i)) for i, s in sets.items()}


def test_jaccard_join(spark, docs, texts, empty):
    want = brute_components([(3 * i, t) for i, t in enumerate(texts)])
    got = [tuple(r) for r in jaccard.link_components(docs).collect()]
    assert len(got) == docs.count()
    assert {g for g in got if g[0] is not None} == set(want.values())
    assert jaccard.link_components(empty).count() == 0


@pytest.mark.parametrize("hot", [200_000, 3])
def test_jaccard_join_chains_and_hot_groups(spark, monkeypatch, hot):
    """Chains whose ends aren't similar, and lists of several blocks."""
    rng = random.Random(6)
    base = [f"w{i}" for i in range(60)]
    rows = []
    for step in range(12):  # each shares most with the one before
        rows.append(" ".join(base))
        at = rng.randrange(57)
        base[at : at + 1] = [f"v{step}"]
    for step in range(40):  # a hub of copies with different edits of different sizes
        w = [f"h{i}" for i in range(50)]
        for _ in range(rng.randrange(4)):
            w[rng.randrange(50)] = f"e{step}"
        rows.append(" ".join(w))
    rows += [rows[3]] * 5
    monkeypatch.setattr(jaccard, "HOT_ROWS", hot)
    monkeypatch.setattr(jaccard, "SMALL", 3)
    monkeypatch.setattr(jaccard, "BLOCK", 7)
    want = brute_components(list(enumerate(rows)))
    got = {tuple(r) for r in jaccard.link_components(table(spark, [(i, t, None) for i, t in enumerate(rows)]).repartition(3)).collect()}
    assert got == set(want.values())


def test_one_of_each(spark, docs):
    left = jaccard.one_of_each(docs)
    assert left.columns != [] and set(left.columns) == set(docs.columns)
    comps = {r.doc_id: r.component_id for r in jaccard.link_components(docs).collect() if r.doc_id is not None}
    assert {r.doc_id for r in left.collect() if r.doc_id is not None} == set(comps.values())


def test_html(spark):
    page = (
        "<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var a='</p>';</script></head><body><header>Site</header><nav><ul><li>Menu</ul></nav><!-- c > --><div class=ad>Buy</div>"
        "<article><header><h1>Head&amp;line</h1></header><p>One <b>bo</b>ld  &#8211;\n x<br>y<p>Two&nbsp;&lt;b&gt;<ul><li>a<li>b</ul><aside>side</aside><form>f</form><section id='comments'><p>reader</p></section></article><footer>&copy;</footer></body></html>"
    )
    rows = [(1, "http://a.example/x", page), (2, None, None), (3, "http://a.example/y", ""), (4, "http://a.example/z", "<p>cut <b>off"), (4, "http://a.example/z", "<p>cut <b>off"), (5, "bad url", "no markup & 1 < 2")]
    pages = spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, text string")
    got = htmltext.extract(pages).collect()
    assert len(got) == len(rows)
    by = {r.page_id: r.text for r in got}
    assert by[1] == "Head&line One bold – x y Two <b> a b"
    assert (by[2], by[3], by[4], by[5]) == ("", "", "cut off", "no markup & 1 < 2")
    assert all(r.n_chars == len(r.text) for r in got)
    assert htmltext.extract(pages.limit(0)).count() == 0


def test_style_tree_removes_what_repeats(spark):
    rng = random.Random(8)
    pages = spark.createDataFrame([(i, f"http://h.example/{i}", f"<body><div class=x1>Always the same line</div><div class=x2>{prose(rng, 30)}</div></body>") for i in range(20)], "page_id long, url string, html string")
    assert not any("Always" in r.text or not r.text for r in htmltext.extract(pages).collect())
    tree = {r.path: r for r in htmltext.importances(htmltext.statistics(pages)).collect()}
    low, high = tree["/body/div.x1"], tree["/body/div.x2"]
    assert low.content == pytest.approx(0.0) and high.content == pytest.approx(1.0) and low.pages == 20 and low.importance < htmltext.IMPORTANCE < high.importance


def test_toxicity(spark, empty):
    rng = random.Random(9)
    bad = ["grumbol", "grumbix", "snarkel"]
    rows, labels = [], []
    for i in range(400):
        w = prose(rng, rng.randrange(30, 80)).split()
        toxic = i % 4 == 0
        if toxic:
            for _ in range(3):
                w[rng.randrange(len(w))] = rng.choice(bad)
        rows.append((i, " ".join(w), "en"))
        labels.append((i, 1, int(toxic), "clash"))
    rows += [(1000, None, "en"), (1001, "", None), (None, "plain stone river", None), (1000, None, "en")]
    labels += [(5, 1, None, ""), (None, 1, 1, ""), (9999, 0, 1, ""), (3, 1, 0, "")]
    labels = spark.createDataFrame(labels, "doc_id long, quality int, toxic int, text string")
    found = toxicity.detect(table(spark, rows), labels).collect()
    assert len(found) == len(rows) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in found)
    held = [r for r in found if r.held_out and r.doc_id is not None and r.doc_id < 400]
    assert len(held) > 40 and all(r.predicted == (r.doc_id % 4 == 0) for r in held)
    assert {r.predicted for r in found if r.doc_id in (None, 1000, 1001)} == {0}
    assert toxicity.detect(empty, labels).count() == 0
    assert {r.score for r in toxicity.detect(table(spark, rows[:3]), labels.where("toxic = 0")).collect()} == {0.0}
    assert {r.score for r in toxicity.detect(table(spark, rows[:3]), labels.limit(0)).collect()} == {0.0}


def test_shards(spark, docs, empty):
    for limit in (200, 5000, 1 << 30):
        got = shards.assign(docs, limit).collect()
        assert len(got) == docs.count()
        sizes, rows = {}, {}
        for r in got:
            sizes[r.shard_id] = sizes.get(r.shard_id, 0) + r.n_bytes
            rows.setdefault(r.shard_id, set()).add(r.doc_id)
            assert len(r.shard_id) == r.local_depth
        assert all(sizes[r.shard_id] == r.shard_bytes for r in got)
        assert all(b <= limit or len(rows[s]) == 1 for s, b in sizes.items())
        names = sorted(sizes)
        assert not any(b.startswith(a) for a, b in zip(names, names[1:], strict=False) if a != b)
        for a in names:  # no split without need: both halves together exceed the limit
            if a and (sib := a[:-1] + ("1" if a[-1] == "0" else "0")) in sizes:
                assert sizes[a] + sizes[sib] > limit
    assert shards.assign(empty).count() == 0


def test_shards_are_written(spark, docs, tmp_path):
    docs = docs.where("doc_id IS NOT NULL").dropDuplicates(["doc_id"])
    placed = shards.write_shards(docs, str(tmp_path / "s"), 5000)
    assert spark.read.parquet(str(tmp_path / "s")).count() == placed.count() == docs.count()


def test_license_keywords_leave_no_match_out():
    """Every set of bigrams that reaches the threshold with a template holds a word that the expression finds."""
    rng = random.Random(10)
    split = lambda x: re.findall(r"[^\W_]+", x.lower())
    grams = [list(dict.fromkeys(f"{a} {b}" for a, b in zip(w, w[1:], strict=False))) for w in (split(x) for _, x in licenses.TEMPLATES)]
    words = licenses.keywords(grams, licenses.THRESHOLD)
    find = re.compile("(?<![a-z0-9])" + licenses.alternatives(words)).search
    assert all(find(f"-{w}.") for w in words) and not find("the river walks")
    for own in grams:
        pairs = sorted(own, key=lambda g: (sum(w in words for w in g.split()), rng.random()))  # those without keywords first
        without = [g for g in pairs if not set(g.split()) & set(words)]
        assert 2 * len(without) < licenses.THRESHOLD * (len(own) + len(without))


def test_license_alternatives():
    rng = random.Random(11)
    for _ in range(50):
        words = ["".join(rng.choice("ab1") for _ in range(rng.randrange(1, 6))) for _ in range(8)]
        exact = re.compile(licenses.alternatives(words) + "$").match
        assert all(exact(w) for w in words)
        assert all(bool(exact(x)) == (x in words) for x in ("".join(rng.choice("ab1") for _ in range(rng.randrange(1, 6))) for _ in range(40)))
