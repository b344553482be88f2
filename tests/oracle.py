"""Comparison of a registered query with its SQL on DuckDB."""

from functools import lru_cache

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@lru_cache(None)
def connection(folder):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    return con


def _text(value):
    if value is None or value != value:
        return "None"
    if isinstance(value, (int, float)) and not isinstance(value, bool):
        return repr(float(value) + 0.0)
    return str(value)


def rows_of(names, rows):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted(tuple(_text(r[i]) for i in order) for r in rows)


def assert_same(df, sql, folder):
    got = rows_of(df.columns, map(tuple, df.collect()))
    relation = connection(folder).sql(sql)
    want = rows_of(relation.columns, relation.fetchall())
    assert sorted(df.columns) == sorted(relation.columns)
    assert len(got) == len(want)
    wrong = [(g, w) for g, w in zip(got, want) if g != w]
    assert not wrong, wrong[:3]
