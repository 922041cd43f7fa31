"""Queries against their oracle SQL in DuckDB, on the smallest tables."""

import duckdb
import pytest

from fixflow.queries import ORACLE, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUICK = [n for n in QUERIES if n in ORACLE and n.split("_")[0] in ("scan", "project", "filter", "case", "join", "cross", "latest", "state", "active", "delta", "agg", "win", "set", "fn", "udaf", "reduce", "cost", "grid", "stats", "degree", "same", "stream")]
QUICK = [n for n in QUICK if n not in ("active_counts_by_superstep",)] + ["pagerank_part_supp", "bgd_squared_lineitem", "bgd_loss_trace_lineitem", "components_turns", "pagerank_exact_part_supp"]


def cells(rows):
    return sorted(tuple("N" if v is None else repr(float(v)) if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    c.sql("set timezone='UTC'")
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_oracle(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    names = sorted(df.columns)
    want = duck.sql(ORACLE[name])
    assert names == sorted(want.columns)
    at = [want.columns.index(n) for n in names]
    assert cells([tuple(r[n] for n in names) for r in df.collect()]) == cells([tuple(r[i] for i in at) for r in want.fetchall()])
