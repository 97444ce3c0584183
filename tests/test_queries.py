"""Registered queries against an independent engine, on the smallest tables."""

import duckdb
import pytest

from rankflow.plans.queries import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
REGISTRY = registry()
#: One of each kind; the driver runs them all.
SOME = [n for n in REGISTRY.sql if n.startswith(("graph_", "join_", "agg_", "set_", "stream_interval", "window_"))] + [
    "pull_step_once", "cold_k20_nation_trade", "frontier_k2_mix", "reach_k5_del", "warm_k5_ins", "frontier_blocked_b2", "batch_normalize", "vertex_add_rescale", "synthetic_ring", "cosine_neighbours",
]


@pytest.fixture(scope="module")
def con(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", SOME)
def test_query(spark, con, sf_dir, name):
    made, found = REGISTRY.queries[name](spark, sf_dir), con.sql(REGISTRY.sql[name])
    columns = sorted(made.columns)
    assert sorted(found.columns) == columns
    at = [found.columns.index(c) for c in columns]
    tidy = lambda x: round(x, 9) if isinstance(x, float) else x
    want = sorted((tuple(tidy(r[k]) for k in at) for r in found.fetchall()), key=str)
    assert sorted((tuple(tidy(r[c]) for c in columns) for r in made.collect()), key=str) == want


def test_entry(spark):
    import __spark_entry__ as entry

    df = entry.entry(spark)
    assert df.count() > 0 and {"id", "rank", "affected"} <= set(df.columns)
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_cosines_of_the_whole_table(spark, con, sf_dir):
    pairs = con.sql("SELECT count(*) FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1").fetchall()[0][0]
    assert pairs > 39 and REGISTRY.queries["cosine_neighbours"](spark, sf_dir).count() == pairs


def test_common_customers_of_all_suppliers(spark, tmp_path):
    orders = [(k, k % 3) for k in range(9)]
    lines = [(k, s) for k in range(9) for s in ((k * 7) % 11, (k * 5 + 3) % 11, 4)]
    spark.createDataFrame(orders, "o_orderkey bigint, o_custkey bigint").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame(lines, "l_orderkey bigint, l_suppkey bigint").write.parquet(f"{tmp_path}/lineitem.parquet")
    buyers = {s: {k % 3 for k, t in lines if t == s} for _, s in lines}
    want = {(a, b, len(buyers[a] & buyers[b])) for a in buyers for b in buyers if a < b and buyers[a] & buyers[b]}
    assert max(b for _, b, _ in want) >= 5
    assert {tuple(r) for r in REGISTRY.queries["two_hop"](spark, str(tmp_path)).collect()} == want


def test_bands_reach_the_dearest_order(spark, tmp_path):
    spark.createDataFrame([(1, 10.0), (2, 50000.0), (3, 599999.0), (4, 600000.0), (5, 1e6)], "o_orderkey bigint, o_totalprice double").write.parquet(f"{tmp_path}/orders.parquet")
    assert {tuple(r) for r in REGISTRY.queries["join_range"](spark, str(tmp_path)).collect()} == {(1, 0), (2, 1), (3, 11), (4, 12), (5, 20)}


def test_full_join_takes_every_nation(spark, sf_dir):
    rows = REGISTRY.queries["join_full"](spark, sf_dir).collect()
    assert {r["n_nationkey"] for r in rows} == set(range(25)) and all(r["n_name"] for r in rows)
