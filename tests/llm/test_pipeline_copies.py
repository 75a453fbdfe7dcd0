"""The pipeline's near copies: five-word shingles, similarity 0.8 or more."""


def shingles(text, k=5):
    w = text.split()
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)}


def test_copies_between_80_and_85_percent_go(spark):
    import corpus_pipeline

    rows, similarity = [], {}
    for i, extra in enumerate((15, 19, 21, 24, 26, 30)):  # a tail of that many new words behind 100
        base = [f"b{i}x{j}" for j in range(104)]
        copy = base + [f"t{i}x{j}" for j in range(extra)]
        a, b = " ".join(base), " ".join(copy)
        similarity[2 * i + 1] = len(shingles(a) & shingles(b)) / len(shingles(a) | shingles(b))
        rows += [(2 * i, a, "en", "s", 0), (2 * i + 1, b, "en", "s", 0)]
    assert sum(0.8 <= s < 0.85 for s in similarity.values()) == 3
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r.doc_id for r in corpus_pipeline.drop_copies(spark, docs, "").collect()}
    assert kept == {r[0] for r in rows} - {i for i, s in similarity.items() if s >= 0.8}


def test_row_numbers(spark, tmp_path):
    """Rows of files are told apart without a copy, others with one; clashing names are avoided."""
    from wedgework.llm.common import numbered

    rows = spark.range(1000).selectExpr("id % 7 AS doc_id", "'t' AS text", "1 AS row", "2 AS row_")
    rows.repartition(5).write.parquet(str(tmp_path / "d"))
    read = spark.read.parquet(str(tmp_path / "d"))
    for docs in (rows, read, read.limit(0), read.join(read.select("doc_id").distinct(), "doc_id")):
        found, key = numbered(docs)
        assert key == "row__" and found.columns == [*docs.columns, key]
        n = docs.count()
        assert found.select(key).distinct().count() == n
        assert found.join(found.select(key, "doc_id"), [key, "doc_id"]).count() == n
