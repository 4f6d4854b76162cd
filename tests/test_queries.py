"""Registered queries against their DuckDB counterparts on the smallest tables."""

import datetime
import decimal
import importlib
import sys

import duckdb
import pytest

from sparseloom.plans import catalog
from sparseloom.sources.tables import SCHEMAS

#: A cross-section; the driver compares all of them.
NAMES = [
    "batches_exact", "node_sample_3hop", "node_positions", "node_sample_distinct", "its_distinct", "race_distinct", "rejection_draws", "layer_sample", "layer_sample_2layer", "grid_spgemm_c2",
    "comm_ledger_aware", "comm_ledger_oblivious", "cost_model_table", "feature_fetch_cached", "feature_mean_1hop", "graph_similar", "graph_relabel", "graph_handoff", "join_asof", "join_interval",
    "agg_cube", "win_range", "udtf_sample_neighbors", "edges_roundtrip", "stream_session", "stream_sliding", "stream_reservoir", "stream_join", "udaf_vector_mean",
]


def norm(v):
    if isinstance(v, decimal.Decimal):
        return float(v)
    if isinstance(v, float):
        return round(v, 6)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None)
    return tuple(norm(x) for x in v) if isinstance(v, (list, tuple)) else v


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_oracle(spark, sf, name):
    df = catalog.QUERIES[name](spark, sf)
    columns = sorted(df.columns)
    con = duckdb.connect()
    con.execute("SET timezone = 'UTC'")
    for t in SCHEMAS:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    found = con.execute(catalog.ORACLES[name])
    names = [c[0] for c in found.description]
    assert sorted(names) == columns
    want = sorted((tuple(norm(r[names.index(c)]) for c in columns) for r in found.fetchall()), key=str)
    assert sorted((tuple(norm(r[c]) for c in columns) for r in df.collect()), key=str) == want


def test_entry_works_without_the_removable_part(spark, sf, monkeypatch):
    import __spark_entry__

    for name in [m for m in sys.modules if m.startswith("sparseloom.llm") or m == "corpus_pipeline"]:
        monkeypatch.delitem(sys.modules, name)
    monkeypatch.setitem(sys.modules, "sparseloom.llm", None)
    monkeypatch.setitem(sys.modules, "corpus_pipeline", None)
    bare = importlib.reload(__spark_entry__)
    assert not any(n.startswith("op") or n == "pipeline" for n in bare.queries())
    assert set(bare.oracle_sql()) <= set(bare.queries())
    assert bare.entry(spark).count() > 0
    monkeypatch.undo()
    importlib.reload(__spark_entry__)
