"""Comparison of a query with its SQL."""

import os


def compare(spark, query, sql, sf_dir):
    """Rows of a query and of its SQL, sorted."""
    import duckdb

    df = query(spark, sf_dir)
    names = sorted(df.columns)
    rows = [tuple(r[c] for c in names) for r in df.collect()]
    db = duckdb.connect()
    for f in os.listdir(sf_dir):
        if f.endswith(".parquet"):
            db.execute(f"CREATE VIEW {f[:-8]} AS SELECT * FROM read_parquet('{sf_dir}/{f}')")
    cur = db.execute(sql)
    got = [x[0] for x in cur.description]
    assert sorted(got) == names
    at = [got.index(c) for c in names]
    want = [tuple(r[i] for i in at) for r in cur.fetchall()]
    key = lambda r: tuple((x is None, str(x)) for x in r)
    return sorted(rows, key=key), sorted(want, key=key)
