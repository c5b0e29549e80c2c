"""Registered queries against their oracles, on the smallest tables."""

import __spark_entry__ as entry
import duckdb
import pytest

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = ["join_asof", "join_semi", "agg_basic", "agg_cube", "win_lead_lag", "set_except_all", "fn_json", "sub_exists", "degree_stats", "graph_session", "tumbling_counts", "clique3", "baseline_triple_w2", "sol_edges_w2", "count_w2", "count_rank_q6", "sink_bucketed", "sink_partitioned", "udf_scalar_pandas"]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_oracle(spark, sf, duck, name):
    df = entry.queries()[name](spark, sf)
    got = sorted(tuple(str(v) for _, v in sorted(zip(df.columns, r))) for r in df.collect())
    out = duck.execute(entry.oracle_sql()[name])
    names = [x[0] for x in out.description]
    assert got == sorted(tuple(str(v) for _, v in sorted(zip(names, r))) for r in out.fetchall())


def test_relaxations_of_a_clique(spark, sf):
    """Of 4 vertices: 1 whole, 6 and 15 connected templates, and the 16 spanning trees."""
    levels = [r.level for r in entry.queries()["udtf_relaxations"](spark, sf).collect()]
    assert [levels.count(k) for k in range(4)] == [1, 6, 15, 16]
