"""Every query with an oracle, against DuckDB on the smallest tables; rows only for the others that are quick."""

from __future__ import annotations

import glob
import os

import duckdb
import pytest

from tests.conftest import TINY
from tracefl import registry

ORACLES = registry.oracles()


def normal(v):
    if isinstance(v, (list, tuple)):
        return [normal(x) for x in v]
    return repr(v + 0.0) if isinstance(v, float) else repr(v)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for p in glob.glob(f"{TINY}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    return con


@pytest.mark.parametrize("name", sorted(n for n in ORACLES if n != "a2f_two_private_rounds"))
def test_parity(spark, duck, name):
    df = registry.queries()[name](spark, TINY)
    rows, columns = df.collect(), sorted(df.columns)
    result = duck.execute(ORACLES[name])
    names = [c[0] for c in result.description]
    assert sorted(names) == columns
    ours = sorted(tuple(str(normal(r[c])) for c in columns) for r in rows)
    theirs = sorted(tuple(str(normal(r[names.index(c)])) for c in columns) for r in result.fetchall())
    assert ours == theirs
