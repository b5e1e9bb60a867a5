"""Registered queries against their SQL twins on the smallest tables, and the plans of some."""

import duckdb
import pytest

import __spark_entry__ as entry
from saferoute.operators.relational import Q as RELATIONAL
from saferoute.plans import method_queries as M

from .conftest import DATA

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = [n for n in [*M.Q, *RELATIONAL] if n in entry.oracle_sql()]


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/sf0.001/{t}.parquet'")
    return con


def norm(x):
    return None if x is None or x != x else round(x, 6) if isinstance(x, float) else x


@pytest.mark.parametrize("name", NAMES)
def test_twin(spark, small, db, name):
    got = entry.queries()[name](spark, small)
    columns = sorted(got.columns)
    cur = db.execute(entry.oracle_sql()[name])
    names = [d[0] for d in cur.description]
    assert sorted(names) == columns
    want = sorted(repr([norm(r[names.index(c)]) for c in columns]) for r in cur.fetchall())
    assert sorted(repr([norm(r[c]) for c in columns]) for r in got.collect()) == want


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def plan(df):
    return df._jdf.queryExecution().toString()


def test_scans_are_pruned_and_boxes_are_equi_joins(spark, small):
    text = plan(RELATIONAL["op_scan_prune"](spark, small))
    assert "PushedFilters: [IsNotNull(l_shipdate)" in text and "l_tax" not in text.split("PushedFilters")[1]
    assert "NestedLoop" not in plan(RELATIONAL["op_join_range_binned"](spark, small))
    assert "NestedLoop" not in plan(M.Q["kw_exact_blocked"](spark, small))


def test_bucketed_probe_needs_no_exchange(spark, small):
    name = RELATIONAL["op_bucketed_lookup"](spark, small)
    assert "Exchange" not in plan(name.groupBy("eid").count()).split("Physical Plan")[1]
