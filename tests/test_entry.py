"""Registered queries against their SQL on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents pages conversations".split()
NAMES = ["graph_basket", "graph_planted", "graph_geo", "coverage", "modularity", "contract", "lp_dominant_step", "move_gain", "consensus_exact", "agglomerate_star_r1", "components_geo", "top_members", "asof_community", "pareto", "best_move", "lp_sync_r3_shuffle", "lp_semi_k2_broadcast", "lp_settled_geo", "move_r3_delta", "multilevel_2level", "agglomerate_matching_level", "profile_pagepages", "profile_turns", "contract_one_task", "sample_nodes", "sample_edges", "sample_spread", "sql_views", "adjacency_lines", "stream_user_state"]


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def rows(columns, values):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted((repr(tuple(round(float(v[i]), 6) if isinstance(v[i], int | float) else v[i] for i in order)) for v in values))


@pytest.mark.parametrize("name", NAMES)
def test_same_rows(spark, db, name):
    df = entry.queries()[name](spark, SF)
    want = db.execute(entry.oracle_sql()[name])
    columns = [d[0] for d in want.description]
    assert sorted(df.columns) == sorted(columns)
    assert rows(df.columns, [tuple(r) for r in df.collect()]) == rows(columns, want.fetchall())
