"""The registered radius search names the documents that it finds."""

from collections import defaultdict

from wedgework.llm import simhash


def test_neighbours_have_ids(spark, tmp_path):
    base = [" ".join(f"w{i}x{j}" for j in range(200)) for i in range(6)]
    rows = [(20 * i, t) for i, t in enumerate(base)] + [(20 * i + 1, t) for i, t in enumerate(base)] + [(20 * i + 2, t + " tail") for i, t in enumerate(base)] + [(3, None), (None, base[0])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    keyed = docs.selectExpr("doc_id", "coalesce(text, '') AS body", "xxhash64(coalesce(text, '')) AS bh")
    fp = [(r.doc_id, r.fp) for r in simhash.fingerprints(keyed, ["doc_id", "bh"]).collect()]
    near = lambda a, b: ((a ^ b) & (1 << 64) - 1).bit_count() <= 3
    want = {(a, b, j) for i, a in fp if i is not None and i % 20 == 0 for j, b in fp if near(a, b)}
    got = simhash.simhash_neighbours(spark, str(tmp_path)).collect()
    of = defaultdict(set)
    for r in got:
        if r.kind == "member":
            of[r.fp].add(r.doc_id)
    assert {(r.query_fp, r.fp, j) for r in got if r.kind == "pair" for j in of[r.fp]} == want
    assert {j for _, _, j in want} >= {0, 1, 20, 21, None}
