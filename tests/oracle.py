"""Compares a query's rows with its DuckDB twin's, order aside."""

import os

import duckdb
import pandas as pd

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir: str, sql: str) -> pd.DataFrame:
    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        p = f"{sf_dir}/{t}.parquet"
        if os.path.exists(p):
            con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{p}{'/*.parquet' if os.path.isdir(p) else ''}')")
    return con.sql(sql).df()


def canonical(df: pd.DataFrame) -> list:
    def cell(x):
        if isinstance(x, float):
            return "null" if x != x else f"{x + 0.0:.6g}" if abs(x) < 1e-4 else f"{round(x, 6) + 0.0:.10g}"
        if x is None or x is pd.NaT or x is pd.NA:
            return "null"
        if isinstance(x, (bool,)) or type(x).__name__ == "bool_":
            return str(bool(x))
        if isinstance(x, int) or type(x).__name__.startswith(("int", "uint")):
            return f"{float(x):.10g}" if abs(int(x)) < 2**50 else str(int(x))
        if hasattr(x, "tolist") and not isinstance(x, str):
            return str([cell(v) for v in x.tolist()])
        if isinstance(x, list):
            return str([cell(v) for v in x])
        return str(x)

    df = df[sorted(df.columns)]
    return sorted(tuple(cell(v) for v in row) for row in df.itertuples(index=False))


def same(spark_df, sf_dir: str, sql: str) -> None:
    got, want = spark_df.toPandas(), duck(sf_dir, sql)
    assert sorted(got.columns) == sorted(want.columns), (sorted(got.columns), sorted(want.columns))
    a, b = canonical(got), canonical(want)
    assert len(a) == len(b), (len(a), len(b))
    wrong = [(x, y) for x, y in zip(a, b, strict=True) if x != y]
    assert not wrong, wrong[:3]
