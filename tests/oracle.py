"""Compares a query with its SQL in DuckDB."""

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def rows(values):
    def one(v):
        return repr(round(v, 6) + 0.0) if isinstance(v, float) else repr(v)

    return sorted(tuple(map(one, r)) for r in values)


def same(spark, sf, query, sql):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df, ref = query(spark, sf), con.sql(sql)
    cols = sorted(df.columns)
    assert cols == sorted(ref.columns)
    got = [tuple(r) for r in df.select(*cols).collect()]
    assert rows(got) == rows(ref.select(",".join(f'"{c}"' for c in cols)).fetchall())
    return got
