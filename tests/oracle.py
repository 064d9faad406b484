"""Compare a Spark result with a SQL text run by DuckDB on the same tables."""

import math

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(folder):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    return c


def _cell(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return "~"
    if isinstance(v, bool) or not hasattr(v, "__float__"):
        return str(v)
    return repr(float(v))


def rows(frame):
    cols = sorted(frame.columns)
    return cols, sorted(tuple(_cell(v) for v in r) for r in frame[cols].itertuples(index=False, name=None))


def assert_same(df, sql, folder):
    got, want = rows(df.toPandas()), rows(connect(folder).execute(sql).df())
    assert got[0] == want[0]
    assert len(got[1]) == len(want[1])
    assert got[1] == want[1]
