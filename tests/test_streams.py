"""Streams against the same computed at once."""

import math

from pyspark.sql import functions as F

from rankflow import graphs
from rankflow.functions import measures
from rankflow.model import Params
from rankflow.operators import methods, snapshot
from rankflow.streaming import edges as st


def test_stateful_degrees_and_handoffs(spark, sf_dir):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    events = st.event_stream(spark, sf_dir)
    got = {r[0]: r[1] for r in st.drained(st.stateful(events, st.DegreeProcessor(), "user_id", "user_id bigint, degree bigint"), "update").collect()}
    want = {r[0]: r[1] for r in spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("user_id").count().collect()}
    assert got == want
    steps = st.drained(st.stateful(events, st.HandoffProcessor(), "k", "src bigint, dst bigint, ts timestamp"), "update")
    assert {tuple(r) for r in steps.select("src", "dst").distinct().collect()} == {tuple(r) for r in graphs.handoff(spark, sf_dir).select("src", "dst").collect()}


def test_maintained_ranks_equal_a_recomputation(spark, sf_dir, tmp_path):
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    base = events.where("event_id < 700")
    named = lambda df: df.select(F.concat(F.lit("u"), "user_id").alias("src"), F.concat("event_type", F.lit(":"), F.get_json_object("props", "$.k")).alias("dst"))
    store, late = str(tmp_path / "store"), str(tmp_path / "late")
    st.start_store(spark, named(base), store)
    events.where("event_id >= 700").coalesce(1).write.parquet(late)
    stream = st.edge_stream(st.event_stream(spark, late, "*.parquet"))
    st.maintain(stream, store, Params(tau=1e-6)).awaitTermination()
    ranks = snapshot.read_version(spark, f"{store}/ranks", 1)
    exact = methods.cold(snapshot.prepare(named(events)), Params(write_every=10)).ranks
    assert ranks.count() == exact.count()
    assert measures.l1(ranks, exact).first()[0] < 1e-3 and math.isclose(ranks.agg(F.sum("rank")).first()[0], 1, abs_tol=1e-6)


def test_maintained_ranks_follow_deletes(spark, tmp_path):
    def named(pairs):
        return spark.createDataFrame([(f"v{a}", f"v{b}") for a, b in pairs], "src string, dst string")

    base = {(k, (k + s) % 30) for k in range(30) for s in (1, 7)}
    steps = [
        ([(0, 15), (3, 31)], [(0, 7), (5, 6), (9, 20)]),  # a new vertex; one delete of an edge that isn't there
        ([(0, 7)], [(0, 15), (12, 13)]),  # an edge comes back, an inserted one goes
    ]
    store, late = str(tmp_path / "store"), str(tmp_path / "late")
    st.start_store(spark, named(sorted(base)), store)
    for ins, dels in steps:
        rows = named(ins).withColumn("op", F.lit("+")).union(named(dels).withColumn("op", F.lit("-")))
        rows.coalesce(1).write.mode("append").parquet(late)
        stream = spark.readStream.schema("src string, dst string, op string").parquet(late)
        st.maintain(stream, store, Params(tau=1e-9)).awaitTermination()
        base = (base | set(ins)) - set(dels)
    ranks = snapshot.read_version(spark, f"{store}/ranks", 2)
    exact = methods.cold(snapshot.prepare(named(sorted(base))), Params(write_every=10)).ranks
    assert ranks.count() == exact.count()
    assert measures.l1(ranks, exact).first()[0] < 1e-6
