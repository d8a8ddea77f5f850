"""A Spark result against DuckDB SQL, or against plain rows, without regard to order."""

import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def database(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        con.sql(f"create view {t} as select * from '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def text(x):
    if x is None or (isinstance(x, float) and x != x):
        return "~"
    if isinstance(x, float):
        return f"{x:.9g}"
    if hasattr(x, "tolist") and not isinstance(x, (str, bytes)):
        x = x.tolist()
    if isinstance(x, (list, tuple)):
        return "[" + ",".join(map(text, x)) + "]"
    if type(x).__name__ == "Decimal":
        return f"{float(x):.9g}"
    return "~" if str(x) in ("<NA>", "NaT", "nan") else str(x)


def rows_of(frame):
    frame = frame[sorted(frame.columns)]
    return sorted(tuple(map(text, r)) for r in frame.itertuples(index=False, name=None))


def same(df, con, sql):
    got, want = df.toPandas(), con.sql(sql).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows_of(got) == rows_of(want)
