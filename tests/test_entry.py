"""The driver contract."""

import __spark_entry__ as entry


def test_names_match():
    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 100


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["v", "deg", "closed", "lcc"] and df.count() == 200


def test_some_queries_against_sql(spark, data):
    """A few queries of each family; the driver compares all of them."""
    import duckdb

    db = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages".split():
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{data}/{t}.parquet'")
    queries, sql = entry.queries(), entry.oracle_sql()
    for name in ("lcc_copurchase", "closed_pairs_succession_directed", "reads_by_parts_copurchase", "hot_set_25_rmat", "query_messages_rmat", "window_graph_triangles"):
        df = queries[name](spark, data)
        cols = sorted(df.columns)
        got = sorted(repr([r[c] for c in cols]) for r in df.collect())
        found = db.execute(sql[name])
        order = [[d[0] for d in found.description].index(c) for c in cols]
        assert got == sorted(repr([r[i] for i in order]) for r in found.fetchall()), name
