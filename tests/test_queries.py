"""Registered queries against their SQL twins, and the entry point."""

import duckdb
import pytest

import __spark_entry__ as e
from canopy.queries import ORACLES, QUERIES

D = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
FAST = [q for q in QUERIES if q.startswith("ops_") and q in ORACLES] + ["cc_conversations", "cc_url", "contract_paths_events", "view_growth_cut8", "probe_cut8", "is_fraction", "subtree_sizes_heap2", "local_roots_heap2", "ports_fk", "stream_tumbling", "stream_sliding", "stream_sessions", "stream_interval_join", "stream_components"]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{D}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", FAST)
def test_sql_twin(spark, duck, name):
    got = QUERIES[name](spark, D)
    want = duck.sql(ORACLES[name])
    names = sorted(got.columns)
    assert names == sorted(want.columns)
    rows = sorted((tuple(r[c] for c in names) for r in got.collect()), key=str)
    assert rows == sorted(want.select(*[duckdb.ColumnExpression(c) for c in names]).fetchall(), key=str)


def test_entry(spark):
    assert e.entry(spark).columns == ["id", "component"]


def test_registry_without_the_subpackage(monkeypatch):
    import builtins

    real = builtins.__import__

    def deny(name, *a, **k):
        if name.startswith("canopy.llm") or name == "corpus_pipeline":
            raise ImportError(name)
        return real(name, *a, **k)

    monkeypatch.setattr(builtins, "__import__", deny)
    assert not [q for q in e.queries() if q.startswith("op") and q[2].isdigit()] and "cc_fk" in e.queries()


def test_oracles_have_queries():
    assert set(e.oracle_sql()) <= set(e.queries())
