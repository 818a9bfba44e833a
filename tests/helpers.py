"""Comparing answers of Spark and DuckDB."""

from collections import Counter

import pandas as pd


def rows_of(frame, columns):
    plain = lambda v: None if pd.isna(v) else round(float(v), 6) if isinstance(v, float) else int(v) if hasattr(v, "dtype") and v.dtype.kind in "iu" else v
    return Counter(tuple(plain(v) for v in row) for row in frame[columns].astype(object).itertuples(index=False))


def assert_same(spark_frame, duck_frame):
    columns = sorted(spark_frame.columns)
    assert columns == sorted(duck_frame.columns)
    assert rows_of(spark_frame, columns) == rows_of(duck_frame, columns)
