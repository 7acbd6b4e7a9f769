"""Comparison of a registered query with its DuckDB SQL."""

import glob
import math
import os

import duckdb


def connection(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    for path in glob.glob(f"{sf_dir}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


def canonical(rows, names) -> list[tuple]:
    order = sorted(range(len(names)), key=lambda i: names[i])

    def plain(v):
        if v is None or (isinstance(v, float) and math.isnan(v)):
            return "null"
        if isinstance(v, float):
            return repr(round(v, 9) + 0.0)
        return str(v)

    return sorted(tuple(plain(r[i]) for i in order) for r in rows)


def same(spark, query, sql: str, sf_dir: str) -> bool:
    df = query(spark, sf_dir)
    want = connection(sf_dir).sql(sql)
    got = canonical([tuple(r) for r in df.collect()], df.columns)
    expected = canonical(want.fetchall(), want.columns)
    as_float = lambda rows: [tuple(repr(float(x)) if x.replace(".", "", 1).replace("-", "", 1).replace("e", "", 1).isdigit() else x for x in r) for r in rows]
    return sorted(df.columns) == sorted(want.columns) and sorted(as_float(got)) == sorted(as_float(expected))
