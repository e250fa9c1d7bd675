"""The driver contract, with and without the llm subpackage."""

import __spark_entry__


def test_entry_and_names(spark):
    import doccurate.plans.catalogue as catalogue

    assert __spark_entry__.entry(spark).count() > 0
    queries, oracles = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(catalogue.QUERIES) <= set(queries) and set(oracles) <= set(queries)


def test_a_query_of_each_kind_agrees_with_sql(spark):
    import duckdb

    sf_dir = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for name in ("documents", "pages", "benchmark", "conversations", "orders", "lineitem", "events"):
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{sf_dir}/{name}.parquet'")
    queries, oracles = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    for name in ("w02_links", "w04_doc_language", "w07_containment", "w11_overlap", "op_agg_rollup", "op_stream_tumbling"):
        found = queries[name](spark, sf_dir)
        columns = sorted(found.columns)
        expected = con.execute(f"SELECT {', '.join(columns)} FROM ({oracles[name]})").fetchall()
        key = lambda r: tuple(round(x, 6) if isinstance(x, float) else x for x in r)
        assert sorted(map(repr, map(key, found.select(*columns).collect()))) == sorted(map(repr, map(key, expected))), name
