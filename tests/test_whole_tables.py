"""Queries over whole tables, against their definitions."""

import duckdb

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"


def rows(spark, name, sql, folder=SF):
    con = duckdb.connect()
    for t in "region supplier pages lineitem orders customer nation".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    got = con.execute(sql)
    names = [d[0] for d in got.description]
    plain = lambda r: tuple(round(x, 9) if isinstance(x, float) else x for x in r)
    return sorted(plain(r) for r in entry.queries()[name](spark, folder).select(*names).collect()), sorted(map(plain, got.fetchall()))


def test_links_are_all_pairs(spark):
    got, want = rows(spark, "scan_links", """WITH h AS (SELECT page_id, unnest(list_distinct(regexp_extract_all(html, 'href="([^"]*)"', 1))) AS href FROM pages),
        n AS (SELECT page_id, count(*) AS n FROM h GROUP BY 1)
        SELECT a.page_id AS src, b.page_id AS dst, count(*)::DOUBLE / any_value(n) AS trust
        FROM h a JOIN h b ON a.href = b.href AND a.page_id < b.page_id JOIN n ON n.page_id = a.page_id GROUP BY 1, 2""")
    assert got == want and want


def test_cross_join_has_all_suppliers(spark):
    got, want = rows(spark, "join_cross", "SELECT r_name, s_suppkey FROM region, supplier", "/root/testdata/sf0.01")
    assert got == want and want


def test_typed_graph_has_all_lines(spark):
    k = [x * 10**13 for x in range(6)]
    got, want = rows(spark, "scan_typed", f"""SELECT {k[1]} + o_custkey AS src, {k[3]} + l_partkey AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey
        UNION SELECT {k[3]} + l_partkey, {k[2]} + l_suppkey FROM lineitem UNION SELECT {k[1]} + c_custkey, {k[4]} + c_nationkey FROM customer
        UNION SELECT {k[2]} + s_suppkey, {k[4]} + s_nationkey FROM supplier UNION SELECT {k[4]} + n_nationkey, {k[5]} + n_regionkey FROM nation""")
    assert got == want and want


def test_broadcast_join_sends_vertices_not_edges(spark, monkeypatch):
    from groupmatch import more_queries

    sql = entry.oracle_sql()["join_broadcast"]
    got, want = rows(spark, "join_broadcast", sql)
    assert got == want and want
    monkeypatch.setattr(more_queries, "_SMALL", 0)
    got, _ = rows(spark, "join_broadcast", sql)
    assert got == want
    assert "strategy=broadcast" not in entry.queries()["join_broadcast"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()


def test_broadcast_join_sends_pieces_of_a_larger_table(spark, monkeypatch):
    import __spark_entry__ as entry
    from groupmatch import more_queries

    monkeypatch.setattr(more_queries, "_SMALL", 60)  # fewer than the vertices
    got, want = rows(spark, "join_broadcast", entry.oracle_sql()["join_broadcast"])
    assert got == want
    assert "strategy=broadcast" in entry.queries()["join_broadcast"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
