"""Registered queries against DuckDB over the smallest tables."""

import os

import duckdb
import pytest

from probejoin import queries_relational, queries_streaming  # noqa: F401
from probejoin.queries import ORACLES, QUERIES
from probejoin.workloads import VARIANTS

SF = "/root/testdata/sf0.001"
SOME = [f"w_{w}_{v}" for w, vs in VARIANTS.items() for v in vs if w in ("l1", "l4", "l8", "s2", "s3a", "s10")] + [
    "si_rows", "stats_exact", "closure_within", "lookup_counts", "rows_moved", "probe_predvar", "probe_multikey", "base_merge", "six_tp_xxo", "join_asof", "join_interval", "win_sessions", "agg_cube", "fn_url", "cogroup_join", "st_late", "st_interval_join", "st_index_append", "sparql_union", "nt_roundtrip", "index_upsert",
]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for f in os.listdir(SF):
        c.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{SF}/{f}'")
    return c


def rows(names, values):
    order = sorted(range(len(names)), key=names.__getitem__)
    show = lambda v: repr(round(float(v), 6)) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)
    return sorted(tuple(show(r[k]) for k in order) for r in values)


@pytest.mark.parametrize("name", SOME)
def test_query(spark, con, name):
    df = QUERIES[name](spark, SF)
    cur = con.execute(ORACLES[name])
    names = [d[0] for d in cur.description]
    assert sorted(df.columns) == sorted(names)
    assert rows(df.columns, df.collect()) == rows(names, cur.fetchall())
