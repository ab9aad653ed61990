"""Queries against their DuckDB twins on the smallest tables."""

from __future__ import annotations

import duckdb
import pandas as pd
import pytest

from corpusforge import oracles, queries
from corpusforge.engine import TABLES

#: Identification queries share their parts; these stand for the rest, which the driver compares.
LID = {"lid_train_counts", "lid_predict_fused", "lid_release_delta", "lid_confused_pairs", "compare_outcomes"}
NAMES = [n for n in oracles.SQL if not n.startswith(("lid_", "compare_")) or n in LID]


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    con.execute("set TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    return con


def rows(df: pd.DataFrame) -> list[tuple]:
    cell = lambda x: "null" if pd.isna(x) else repr(float(x)) if isinstance(x, (float, int)) and not isinstance(x, bool) else str(x)
    return sorted(tuple(cell(x) for x in r) for r in df[sorted(df.columns)].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_twin(spark, small, duck, name):
    got, want = queries.QUERIES[name](spark, small).toPandas(), duck.execute(oracles.SQL[name]).fetchdf()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_every_twin_has_its_query():
    assert set(oracles.SQL) <= set(queries.QUERIES)
