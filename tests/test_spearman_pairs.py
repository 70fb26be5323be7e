import __spark_entry__


def test_all_device_pairs_equal_sql(spark):
    import duckdb

    d = "/root/testdata/sf0.001"
    got = {(r.e1, r.e2): r["corr"] for r in __spark_entry__.queries()["op_spearman_pairs"](spark, d).collect()}
    db = duckdb.connect()
    db.execute(f"CREATE VIEW events AS SELECT * FROM '{d}/events.parquet'")
    want = {(a, b): c for a, b, c in db.execute(__spark_entry__.oracle_sql()["op_spearman_pairs"]).fetchall()}
    assert got.keys() == want.keys() and len(got) == 50
    assert all(abs(got[k] - want[k]) < 2e-6 for k in got)
