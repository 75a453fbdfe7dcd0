"""Chains whose labels rise along them."""

from wedgework.llm import jaccard


def test_rising_chain_is_one_component(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(100)], "a long, b long").coalesce(1)
    assert {tuple(r) for r in jaccard.components(edges).collect()} == {(i, 0) for i in range(101)}


def test_rounds_of_a_rising_chain(spark, monkeypatch):
    """Contraction takes a share of the nodes in each round: 400 nodes need far fewer than 400 rounds."""
    written = []
    plain = jaccard.materialise
    monkeypatch.setattr(jaccard, "materialise", lambda df, label, **more: written.append(label) or plain(df, label, **more))
    edges = spark.createDataFrame([(i, i + 1) for i in range(400)], "a long, b long").coalesce(1)
    assert {r.label for r in jaccard.components(edges).collect()} == {0}
    assert written.count("parent") <= 14
