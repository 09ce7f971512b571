"""Comparison of a query with its SQL in DuckDB."""

from __future__ import annotations

import glob
import os

import duckdb

SF = "/root/testdata/sf0.001"


def database(sf_dir: str = SF):
    db = duckdb.connect()
    for path in glob.glob(f"{sf_dir}/*.parquet"):
        db.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return db


def rows(columns: list[str], found) -> list[tuple]:
    order = sorted(range(len(columns)), key=lambda i: columns[i])

    def plain(v):
        if isinstance(v, float):
            return "null" if v != v else repr(v + 0.0)
        return "null" if v is None else str(v)

    return sorted(tuple(plain(r[i]) for i in order) for r in found)


def assert_equal(spark, query, sql: str, sf_dir: str = SF) -> None:
    df = query(spark, sf_dir)
    result = database(sf_dir).execute(sql)
    names = [d[0] for d in result.description]
    assert sorted(df.columns) == sorted(names)
    assert rows(df.columns, df.collect()) == rows(names, result.fetchall())
