"""Queries against their SQL at the smallest scale."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from veilstream.operators import queries as own


def near(rows):
    return sorted(repr(tuple(round(v, 5) + 0.0 if isinstance(v, float) else str(v) for v in r)) for r in rows)


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.execute(f"create view {f[:-8]} as select * from '{sf}/{f}'")
    return c


@pytest.mark.parametrize("name", sorted(own.oracle_sql()))
def test_oracle(spark, sf, con, name):
    df = own.queries()[name](spark, sf)
    cols = sorted(df.columns)
    q = con.execute(own.oracle_sql()[name])
    names = [d[0] for d in q.description]
    assert sorted(names) == cols
    want = [[r[names.index(c)] for c in cols] for r in q.fetchall()]
    got = [[r[c] for c in cols] for r in df.collect()]
    assert len(got) == len(want)
    assert near(got) == near(want)


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_registry_has_no_sql_without_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


#: Queries that once made their rows on the driver or from a range.
ON_TABLES = ["calibration", "eps_sweep_thresholds", "ledger", "node_noise", "prefix_bottom_up", "prefix_plain", "prefix_variance", "tau_per_trigger", "uniform_key_loads"]


@pytest.mark.parametrize("name", ON_TABLES)
def test_query_reads_a_given_table(spark, sf, name):
    assert any(f.startswith(f"file://{sf}/") for f in own.queries()[name](spark, sf).inputFiles())
