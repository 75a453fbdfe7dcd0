"""The corpus pipeline on a small folder of tables: each stage's decisions take effect on the next."""

import random


def test_pipeline(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(5)
    words = "the of and to in is that it was for on are with as be this have from river stone morning light".split()
    text = lambda n: " ".join(rng.choice(words) + (str(rng.randrange(30)) if rng.random() < 0.3 else "") for _ in range(n))
    rows = [(i, text(60), "en", "s", 0) for i in range(120)]
    toxic = set(range(0, 120, 4))
    rows = [(i, t + " grumbol grumbix snarkel" * 2 if i in toxic else t, g, s, n) for i, t, g, s, n in rows]
    rows += [(200, rows[1][1], "en", "s", 0), (201, rows[1][1] + " more", "en", "s", 0), (202, "12 34 56", "en", "s", 0), (203, None, "en", "s", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(i, 1, int(i in toxic)) for i in range(120)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    kept, at = [], docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        at = stage(spark, at, str(tmp_path)).cache()
        assert at.columns == docs.columns, name
        kept.append({r.doc_id for r in at.collect()})
    every = {r[0] for r in rows}
    assert kept[0] == every - toxic
    assert kept[1] == kept[0] - {202, 203}
    assert kept[2] == kept[1] - {200, 201}
    packed = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert {r.doc_id for r in packed} == kept[2]
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "language_id", "ngram_jaccard_join", "packing"]


SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, row long, label string, k int, score double"


def test_stages_decide_by_row(spark, tmp_path):
    """Null and repeated ids, columns that operators use themselves, a very long text, an empty table."""
    import corpus_pipeline

    rng = random.Random(7)
    words = "the of and to in is that it was for on are with as be this have from river stone morning light".split()
    text = lambda n: " ".join(rng.choice(words) + (str(rng.randrange(40)) if rng.random() < 0.3 else "") for _ in range(n))
    bad = " grumbol grumbix snarkel" * 3
    rows = [(i, text(rng.choice((20, 60, 200, 900, 4000))) + (bad if i % 4 == 0 else "")) for i in range(120)]
    more = [(None, text(60) + bad), (None, text(60)), (None, None), (7, text(60)), (7, rows[7][1]), (7, rows[7][1]), (None, rows[11][1]), (500, text(20000)), (501, ""), (500, text(70))]
    of = lambda r: [(i, t, "en", "s", 0, 3, "x", 1, 0.5) for i, t in r]
    docs = spark.createDataFrame(of(rows + more), SCHEMA)
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(i, 1, int(i % 4 == 0)) for i in range(120)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))

    def kept(stage, at):
        out = stage(spark, at, str(tmp_path))
        assert out.columns == docs.columns
        return out.cache(), sorted(((r.doc_id is None, r.doc_id, r.text) for r in out.collect()), key=repr)

    key = lambda r: [(i is None, i, t) for i, t in r]
    clean = [r for r in rows if r[0] % 4] + [r for r in more if not r[1] or "grumbol" not in r[1]]
    at, got = kept(corpus_pipeline.drop_toxic, docs)
    assert got == sorted(key(clean), key=repr)
    at, got = kept(corpus_pipeline.drop_unknown_language, at)
    read = [r for r in clean if r[1]]
    assert got == sorted(key(read), key=repr)
    at, got = kept(corpus_pipeline.drop_copies, at)
    once = {t: min((i is None, i or 0) for i, x in read if x == t) for _, t in read}
    assert got == sorted([(none, None if none else i, t) for t, (none, i) in once.items()], key=repr)
    assert {r.doc_id for r in corpus_pipeline.pack(spark, at, "").collect()} == {i for _, i, _ in got}
    empty = docs.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        empty = stage(spark, empty, str(tmp_path))
        assert empty.count() == 0


def test_large_group_of_near_copies_makes_rows_in_proportion(spark):
    """2000 texts of one template with their own edits: many similar, none of the frames has more than a few rows for each."""
    from wedgework.llm import jaccard

    rng = random.Random(8)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for i in range(2000):
        own = list(base)
        for _ in range(rng.randrange(1, 7)):
            own[rng.randrange(120)] = f"e{i}x{rng.randrange(3)}"
        rows.append((i, " ".join(own)))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    k, percent = 4, 85
    context = spark.sparkContext
    counts = jaccard.bucket_counts(jaccard.sets_pass(docs, k, ["doc_id"]))
    lists = jaccard.list_pass(jaccard.prefixes(docs, context.broadcast(counts), k, percent), percent).cache()
    links = jaccard.links_of(docs, counts, k, percent)
    assert lists.count() < 60 * len(rows) and links.count() < 60 * len(rows)
    got = {r.doc_id: r.component_id for r in jaccard.link_components(docs, k, percent).collect()}
    sets = [{tuple(w[j : j + k]) for j in range(len(w) - k + 1)} for w in (t.split() for _, t in rows)]
    up = list(range(len(rows)))

    def root(x):
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if root(a) != root(b) and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                up[y] = x
    assert got == {i: root(i) for i in range(len(rows))}
