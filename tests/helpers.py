"""Shared by the tests."""

import os

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def same_rows(spark_df, duck_df) -> bool:
    a, b = spark_df.toPandas(), duck_df
    assert sorted(a.columns) == sorted(b.columns)
    cols = sorted(a.columns)
    rows = lambda df: sorted(tuple(map(str, r)) for r in df[cols].itertuples(index=False))
    return rows(a) == rows(b)
