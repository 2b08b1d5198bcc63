"""Every registered query of the engine with a SQL twin equals it."""

import os

import duckdb
import pandas as pd
import pytest

from flextensor.queries import ORACLES, QUERIES

SLOW = {"q_tests50"}


@pytest.fixture(scope="module")
def con(data):
    c = duckdb.connect()
    for f in os.listdir(data):
        c.execute(f"create view {f.split('.')[0]} as select * from '{data}/{f}'")
    return c


@pytest.mark.parametrize("name", sorted(set(ORACLES) - SLOW))
def test_twin(spark, data, con, name):
    got, want = QUERIES[name](spark, data).toPandas(), con.execute(ORACLES[name]).df()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns)
    a, b = (x[cols].sort_values(cols).reset_index(drop=True) for x in (got, want))
    pd.testing.assert_frame_equal(a, b, check_dtype=False, check_exact=True)
