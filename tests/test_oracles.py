"""Queries against their SQL on the smallest tables."""

import os

import pandas as pd
import pytest

from probsum import queries

queries.load()
# fitted summaries need more sweeps than these queries give on so few rows
FITTED = ("recover_", "est_", "sink_summary", "udtf_")
NAMES = [
    k for k, f in queries.QUERIES.items()
    if k in queries.ORACLES and not getattr(f, "__module__", "").endswith("streams") and not k.startswith(FITTED)
]


@pytest.fixture(scope="module")
def con(sf):
    import duckdb

    c = duckdb.connect()
    c.sql("set timezone = 'UTC'")
    for f in os.listdir(sf):
        c.sql(f"create view {f.removesuffix('.parquet')} as select * from '{sf}/{f}'")
    return c


def normal(df: pd.DataFrame) -> pd.DataFrame:
    cols = sorted(df.columns)

    def plain(v):
        if v is None or v != v:
            return "null"
        return repr(round(float(v), 6)) if hasattr(v, "__float__") and not isinstance(v, str) else str(v)

    return df[cols].map(plain).sort_values(cols).reset_index(drop=True)


@pytest.mark.parametrize("name", NAMES)
def test_oracle(spark, sf, con, name):
    got = normal(queries.QUERIES[name](spark, sf).toPandas())
    want = normal(con.sql(queries.ORACLES[name]).df())
    pd.testing.assert_frame_equal(got, want)
