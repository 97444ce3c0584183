"""Queries of the relational surface on tables beyond the smallest."""

import random

import duckdb
import pytest

from rankflow import graphs
from rankflow.plans.queries import registry

REGISTRY = registry()


def test_recursion_beyond_a_million_rows(spark, tmp_path):
    first, n = 1 << 40, 25_000
    spark.range(first, first + n).selectExpr("id AS p_partkey").write.parquet(f"{tmp_path}/part.parquet")
    walks = REGISTRY.queries["recursion_depth"](spark, str(tmp_path))
    found = walks.selectExpr("count(*)", "min(depth)", "max(depth)", "sum(total)").first()
    assert tuple(found) == (n, 40, 40, sum(p >> k for p in range(first, first + n) for k in range(41)))


def test_nearest_of_blocks_copies_and_odd_vectors(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(graphs, "VECTORS", 6)
    draw = random.Random(4)
    rows = [(k, 1, [float(draw.randint(-3, 3)) for _ in range(3)]) for k in range(60)]  # many at the same angle
    rows += [(k, 2, [1.0, 2.0, 3.0]) for k in range(100, 120)] + [(k, 2, [1.0, 2.0, k / 100]) for k in range(120, 125)]
    rows += [(200, 3, [1.0, 0.0, 0.0]), (201, 3, None), (202, 3, [1.0, 1.0, 0.0]), (203, 3, None), (204, 4, [1.0, 1.0, 1.0]), (205, 5, [0.0, 0.0, 0.0]), (206, 5, [1.0, 1.0, 1.0]), (207, None, [1.0, 1.0, 1.0])]
    spark.createDataFrame(rows, "vec_id bigint, label int, embedding array<float>").repartition(3).write.parquet(f"{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    want = sorted(con.sql(REGISTRY.sql["graph_near_vecs"]).fetchall())
    assert sorted(map(tuple, REGISTRY.queries["graph_near_vecs"](spark, str(tmp_path)).collect())) == want


@pytest.mark.parametrize("name", ["graph_walkthrough", "synthetic_ring"])
def test_graphs_by_rule_are_over_the_customers(spark, tmp_path, name):
    keys = [*range(40), 100, 101, 116]
    spark.createDataFrame([(k,) for k in keys], "c_custkey bigint").repartition(3).write.parquet(f"{tmp_path}/customer.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW customer AS SELECT * FROM '{tmp_path}/customer.parquet/*.parquet'")
    got = sorted(map(tuple, REGISTRY.queries[name](spark, str(tmp_path)).select("src", "dst").collect()))
    assert got == sorted(con.sql(f"SELECT src, dst FROM ({REGISTRY.sql[name]})").fetchall())
    if name == "synthetic_ring":
        assert got == sorted(zip(keys, [*keys[1:], keys[0]], strict=True))
    else:
        steps = [tuple(int(x) for x in e.split("-")) for e in graphs.WALK.split()]
        assert got == sorted((c + a - 1, c + b - 1) for c in range(0, 128, 16) for a, b in steps if {c + a - 1, c + b - 1} <= set(keys))
