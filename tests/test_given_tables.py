"""Scores and generated graphs take their rows from given tables."""

import duckdb
import pytest

import __spark_entry__ as entry
from test_entry import rows

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["quality_vs_baseline", "scores", "pareto"])
def test_scores_of_orders(spark, tmp_path, name):
    """The result follows the table: with its larger half, other rows than with the whole, both as the SQL gives them."""
    found = []
    for where in ("true", "o_orderkey % 2 = 0 OR o_custkey % 3 = 0"):
        folder = tmp_path / str(len(found))
        folder.mkdir()
        db = duckdb.connect()
        db.execute(f"CREATE TABLE orders AS SELECT * FROM '{SF}/orders.parquet' WHERE {where}")
        db.execute(f"COPY orders TO '{folder}/orders.parquet'")
        df = entry.queries()[name](spark, str(folder))
        want = db.execute(entry.oracle_sql()[name])
        columns = [c[0] for c in want.description]
        found.append(rows(df.columns, [tuple(r) for r in df.collect()]))
        assert found[-1] == rows(columns, want.fetchall())
    assert found[0] != found[1]


@pytest.mark.parametrize("name", ["two_density", "heavy_tail", "recursive_matrix", "hyperbolic"])
def test_generators_grow_with_their_table(spark, tmp_path, name):
    """Edges are fewer on a half of the rows, no end is outside the nodes, and a second run draws the same."""
    found = []
    for keep in (2, 1):
        folder = tmp_path / str(keep)
        folder.mkdir()
        duckdb.sql(f"COPY (SELECT * FROM '{SF}/orders.parquet' WHERE o_custkey % {keep} = 0) TO '{folder}/orders.parquet'")
        found.append([sorted(map(tuple, entry.queries()[f"generator_{name}"](spark, str(folder)).collect())) for _ in range(2)])
        assert found[-1][0] == found[-1][1]
    half, whole = found[0][0], found[1][0]
    assert 0 < len(half) < len(whole)
    n = duckdb.sql(f"SELECT count(DISTINCT o_custkey) FROM '{SF}/orders.parquet'").fetchall()[0][0]
    assert all(u < v and w >= 1 for u, v, w in whole)
    assert name == "recursive_matrix" or max(v for _, v, _ in whole) < n
