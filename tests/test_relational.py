"""Statements of the relational surface on odd rows, against their SQL in DuckDB."""

import os

import duckdb

import __spark_entry__


def both(spark, folder, name, **tables):
    """Rows of a query and of its SQL on small tables (rows, schema)."""
    con = duckdb.connect()
    for t, (rows, schema) in tables.items():
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{folder}/{t}.parquet")
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet/*.parquet'")
    df = __spark_entry__.queries()[name](spark, str(folder))
    key = lambda r: [(x is None, x) for x in r]
    return df, sorted(map(tuple, df.collect()), key=key), sorted(con.execute(__spark_entry__.oracle_sql()[name]).fetchall(), key=key)


def test_lateral_topk_ranks_after_the_shuffle(spark, tmp_path):
    orders = [(i, i % 5, float(i % 3)) for i in range(90)] + [(None, 1, 2.0), (None, 2, 9.0), (300, 3, None), (301, None, 9.0)]
    df, got, want = both(
        spark, tmp_path, "join_lateral_topk",
        customer=([(c,) for c in (0, 1, 2, 3, 3, 4, 7, None)], "c_custkey long"),
        orders=(orders, "o_orderkey long, o_custkey long, o_totalprice double"),
    )
    assert got == want and len(got) == 12
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    windows = [x for x in plan.split("\n") if "Window" in x and "row_number()" in x]
    assert windows and all("o_totalprice" in x for x in windows)  # without an order, rows arrive as the shuffle brings them


def test_recursive_path_walks_the_orders(spark, tmp_path):
    keys = [1, 2, 4, 5, 8, 10, 16, 64, None]  # 32 is missing, so the path ends at 16
    df, got, want = both(spark, tmp_path, "cte_recursive_path", orders=([(k,) for k in keys], "o_orderkey long"))
    assert got == want == [(1, 0), (2, 1), (4, 2), (8, 3), (16, 4)]


def test_binary_scan_reads_the_file(spark):
    df = __spark_entry__.queries()["scan_binary_files"](spark, "/root/testdata/sf0.001")
    assert [r["length"] for r in df.collect()] == [os.path.getsize("/root/testdata/sf0.001/nation.parquet")]
    assert df.columns == ["path", "length"] and "content:binary" in df._jdf.queryExecution().executedPlan().toString()
