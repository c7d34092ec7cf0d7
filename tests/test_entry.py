import __spark_entry__ as entry


def test_registry_is_consistent():
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(q) > 90


def test_flagship(spark):
    assert entry.entry(spark).count() > 0


def test_catalog_oracles_on_the_smallest_tables(spark):
    import duckdb

    from tupleguard.sources import TABLES
    from tupleguard.workloads import catalog

    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    for name in ("inline_q1", "two_pass_q3", "replay_rows_q6", "union_mask", "outer_mask", "intersect_mult", "sink_insert", "transform_fix", "selfjoin_linear"):
        df = catalog.QUERIES[name](spark, d)
        cols = sorted(df.columns)
        got = sorted(map(repr, (tuple(r[c] for c in cols) for r in df.collect())))
        res = con.execute(catalog.ORACLES[name])
        names = [x[0] for x in res.description]
        want = sorted(map(repr, (tuple(r[names.index(c)] for c in cols) for r in res.fetchall())))
        assert got == want, name


def test_guards_of_whole_orders(spark):
    import duckdb

    from tupleguard.sources import TABLES
    from tupleguard.workloads import catalog

    d = "/root/testdata/sf0.01"
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    for name in ("balance_join", "sink_update_state"):
        assert "< 400" not in catalog.ORACLES[name] and "< 1000" not in catalog.ORACLES[name]
        df = catalog.QUERIES[name](spark, d)
        cols = sorted(df.columns)
        want = con.execute(f"select {', '.join(cols)} from ({catalog.ORACLES[name]})").fetchall()
        assert sorted(map(tuple, (tuple(r[c] for c in cols) for r in df.collect()))) == sorted(want), name
    assert con.execute(f"select count(*) from ({catalog.ORACLES['sink_update_state']})").fetchone() == con.execute("select count(*) from orders").fetchone()
