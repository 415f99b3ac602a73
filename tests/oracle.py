"""Runs a query in Spark and its SQL in DuckDB on the same tables and compares the rows."""

import duckdb
import pandas as pd

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def _rows(frame: pd.DataFrame) -> list[tuple]:
    frame = frame[sorted(frame.columns)]

    def plain(x):
        if x is None or (isinstance(x, float) and x != x):
            return "NULL"
        if hasattr(x, "__len__") and not isinstance(x, str):
            return str(list(x))
        return repr(float(x)) if isinstance(x, float) else str(x)

    return sorted(tuple(plain(x) for x in row) for row in frame.itertuples(index=False))


def same(spark, sf, query, sql) -> None:
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    ours, theirs = query(spark, sf).toPandas(), con.execute(sql).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    assert _rows(ours) == _rows(theirs)
