"""The rank engine: closed forms, the walk-through, and what must hold between methods."""

import math

import pytest
from pyspark.sql import functions as F

from rankflow import graphs
from rankflow.functions import measures, udfs
from rankflow.model import Batch, Params
from rankflow.operators import batches, kernel, mark, methods, snapshot
from rankflow.sources.edges import read_edge_list, read_matrix_market, synthetic
from rankflow.storage import written


#: Few rounds: each is a job or two.
QUICK = Params(tau=1e-5, tau_f=1e-9)


def edges(spark, *pairs):
    return spark.createDataFrame(list(pairs) or [], "src bigint, dst bigint")


def ids(df):
    return {r[0] for r in df.collect()}


def rank_of(df):
    return {r["id"]: r["rank"] for r in df.collect()}


def plain(pairs, alpha=0.85, rounds=400, loops=True):
    """The fixed point in plain Python."""
    vertices = sorted({x for e in pairs for x in e})
    g = set(pairs) | ({(v, v) for v in vertices} if loops else set())
    out = {v: sum(s == v for s, _ in g) for v in vertices}
    rank = dict.fromkeys(vertices, 1 / len(vertices))
    for _ in range(rounds):
        new = dict.fromkeys(vertices, (1 - alpha) / len(vertices))
        for s, d in g:
            new[d] += alpha * rank[s] / out[s]
        rank = new
    return rank


@pytest.mark.parametrize(("pairs", "want"), [([(0, 1)], {0: 0.075 / 0.575, 1: 1 - 0.075 / 0.575}), ([(k, 0) for k in range(1, 5)], {1: 0.03 / 0.575, 0: 1 - 4 * 0.03 / 0.575}), ([(k, (k + 1) % 6) for k in range(6)], {k: 1 / 6 for k in range(6)})])
def test_closed_forms(spark, pairs, want):
    result = methods.cold(snapshot.prepare(edges(spark, *pairs)), Params(write_every=10))
    got = rank_of(result.ranks)
    assert result.converged and all(math.isclose(got[v], r, abs_tol=1e-8) for v, r in want.items())
    assert abs(sum(got.values()) - 1) < 1e-12


def test_dead_ends(spark):
    e = edges(spark, (0, 1))
    lost = rank_of(methods.cold(snapshot.prepare(e, dead="none"), Params(dead_ends="none", write_every=5)).ranks)
    assert sum(lost.values()) < 0.5
    shared = rank_of(methods.cold(snapshot.prepare(e, dead="teleport"), Params(dead_ends="teleport", max_iter=25, stop=False)).ranks)
    assert abs(sum(shared.values()) - 1) < 1e-9 and math.isclose(shared[0], 1 / 2.85, abs_tol=1e-3)
    g = snapshot.prepare(e, dead="teleport")
    with pytest.raises(ValueError, match="dead_ends"):
        methods.frontier(g, g, Batch(e, e.limit(0)), shared and methods.uniform(g))


def test_walkthrough_marks(spark):
    for dead, more in (("none", set()), ("selfloop", {2})):
        g = snapshot.prepare(graphs.walkthrough(spark), dead=dead)
        batch = Batch(edges(spark, (4, 12)), edges(spark, (2, 1)))
        new = snapshot.after(g, batch)
        assert ids(mark.initial(new, batch)) == {1, 3, 4, 8, 12} | more
        one = spark.createDataFrame([(1,), (12,)], "id bigint")
        assert ids(mark.expand(new, one)) == {3, 5, 11, 14} | ({1, 12} if more else set())
        two = spark.createDataFrame([(3,), (5,), (11,), (14,)], "id bigint")
        assert ids(mark.expand(new, two)) == {4, 6, 15} | ({3, 5, 11, 14} if more else set())


@pytest.fixture(scope="module")
def chain(spark):
    """A chain of 30 with a few shortcuts, its ranks, and a batch near one end."""
    pairs = [(k, k + 1) for k in range(30)] + [(k + 1, k) for k in range(30)] + [(5, 9), (20, 24)]
    g = snapshot.materialised(snapshot.prepare(edges(spark, *pairs)))
    before = methods.kept(methods.cold(g, Params(tau=1e-6, write_every=5)).ranks)
    batch = snapshot.normalize(Batch(edges(spark, (2, 7), (5, 9), (3, 3)), edges(spark, (1, 2), (28, 10))), g.edges)
    batch = Batch(written(batch.ins, "i"), written(batch.dels, "d"))
    new = snapshot.after(g, batch)
    want = plain([p for p in pairs if p != (1, 2)] + [(2, 7)])
    return g, before, batch, new, want


def test_batch_is_normalised(chain):
    _, _, batch, _, _ = chain
    assert {tuple(r) for r in batch.signed().collect()} == {(2, 7, "+"), (1, 2, "-")}


@pytest.mark.parametrize("method", methods.METHODS)
def test_methods_reach_the_fixed_point(chain, method):
    g, before, batch, new, want = chain
    result = methods.run(method, g, new, batch, before, QUICK)
    got = rank_of(result.ranks)
    assert result.converged and got.keys() == want.keys()
    assert sum(abs(got[v] - r) for v, r in want.items()) < 1e-3
    assert all(r >= 0.15 / new.n - 1e-15 for r in got.values())
    bound = measures.residual(new, result.ranks).first()["certificate"]
    assert sum(abs(got[v] - r) for v, r in want.items()) <= bound + 1e-12


def test_frontier_stays_inside_reach(chain):
    g, before, batch, new, _ = chain
    loose = methods.frontier(g, new, batch, before, QUICK.but(tau_f=1e-4))
    tight = methods.frontier(g, new, batch, before, QUICK.but(tau_f=0.0))
    reached = ids(mark.reach_set(g, new, batch))
    assert ids(loose.affected) <= ids(tight.affected) <= reached
    assert len(ids(loose.affected)) < len(reached)
    counts = [t["affected"] for t in loose.telemetry]
    assert counts == sorted(counts) and loose.vertex_updates == sum(counts)
    old, now = rank_of(before), rank_of(loose.ranks)
    assert all(now[v] == old[v] for v in old.keys() - ids(loose.affected))
    never = methods.frontier(g, new, batch, before, Params(tau_f=math.inf, max_iter=3, stop=False))
    assert ids(never.affected) == ids(mark.initial(new, batch))


@pytest.mark.parametrize("discipline", ["blocked", "local"])
def test_disciplines_agree(chain, discipline):
    g, before, batch, new, want = chain
    for method in ("warm", "frontier"):
        got = rank_of(methods.run(method, g, new, batch, before, QUICK.but(discipline=discipline)).ranks)
        assert sum(abs(got[v] - r) for v, r in want.items()) < 1e-3


def test_empty_batch_and_its_inverse(chain, spark):
    g, before, batch, new, _ = chain
    none = Batch(edges(spark), edges(spark))
    still = methods.frontier(g, g, none, before, QUICK)
    assert rank_of(still.ranks) == rank_of(before) and still.converged and still.vertex_updates == 0
    there = methods.frontier(g, new, batch, before, QUICK)
    back = methods.frontier(new, g, Batch(batch.dels, batch.ins), there.ranks, QUICK)
    assert measures.l1(back.ranks, before).first()[0] < 1e-3


def test_snapshots(chain, tmp_path, spark):
    g, _, batch, new, _ = chain
    again = snapshot.diff(g.edges, new.edges)
    assert {tuple(r) for r in again.signed().collect()} == {tuple(r) for r in batch.signed().collect()}
    degrees = {tuple(r) for r in snapshot.update_degrees(snapshot.out_degrees(g.edges), batch).collect()}
    assert degrees == {tuple(r) for r in snapshot.out_degrees(new.edges).collect()}
    snapshot.write_version(new.edges, str(tmp_path / "e"), 3)
    assert snapshot.read_version(spark, str(tmp_path / "e"), 3).count() == new.edges.count()
    with pytest.raises(ValueError, match="names a vertex"):
        snapshot.normalize(Batch(edges(spark, (1, 999)), edges(spark)), g.edges, g.vertices)


def test_grown_graph_is_exact(chain, spark):
    g, before, _, _, _ = chain
    added = spark.createDataFrame([(500,), (501,)], "id bigint")
    wider = snapshot.prepare(g.edges, g.vertices.union(added))
    ranks = snapshot.rescale(before, g.n, g.n + 2, added)
    old = measures.residual(g, before).first()["residual"]
    assert measures.residual(wider, ranks).first()["residual"] <= old + 1e-12


def test_push_equals_pull(chain):
    g, before, _, _, _ = chain
    step = kernel.pull_step(g, before, 0.85)
    bumped = before.withColumn("rank", F.when(F.col("id") == 3, F.col("rank") + 0.01).otherwise(F.col("rank")))
    pushed = {r[0]: r[1] for r in kernel.push_delta(g, before.where("id = 3").selectExpr("id", "0.01D AS change"), 0.85).collect()}
    a, b = rank_of(step), rank_of(kernel.pull_step(g, bumped, 0.85))
    assert all(abs(b[v] - a[v] - pushed.get(v, 0.0)) < 1e-15 for v in a)


def test_maintain(chain, spark):
    g, before, batch, _, want = chain
    last = list(methods.maintain(g, before, [batch, Batch(edges(spark, (20, 23)), edges(spark))], QUICK, refresh_every=2))
    assert [r.method for _, r in last] == ["frontier", "warm"] and last[1][0].n == len(want)


@pytest.mark.parametrize("small", [0, 100, 60])
def test_regimes_agree(chain, monkeypatch, small):
    """On tables from the start, on arrays of a region, and from arrays to tables when marks outgrow them."""
    g, before, batch, new, _ = chain
    params = Params(max_iter=4, stop=False, tau_f=1e-9)
    want = methods.frontier(g, new, batch, before, params)
    monkeypatch.setattr(methods, "SMALL", small)
    got = methods.frontier(g, new, batch, before, params)
    a, b = rank_of(want.ranks), rank_of(got.ranks)
    assert all(math.isclose(a[v], b[v], rel_tol=1e-12) for v in a) and ids(want.affected) == ids(got.affected)
    assert [t["affected"] for t in want.telemetry] == [t["affected"] for t in got.telemetry]
    assert [t["in_edges"] for t in want.telemetry] == [t["in_edges"] for t in got.telemetry]


def test_a_round_reads_what_is_marked(chain):
    g, before, batch, new, _ = chain
    few = methods.frontier(g, new, batch, before, Params(max_iter=3, stop=False, tau_f=math.inf))
    full = methods.warm(new, before, Params(max_iter=3, stop=False))
    into = new.edges.join(few.affected.selectExpr("id AS dst"), "dst").count()
    assert [t["in_edges"] for t in few.telemetry] == [into] * 3 and into < new.edges.count() / 2
    assert few.edges_read < full.edges_read and few.vertex_updates < full.vertex_updates
    assert set(ids(new.edges_w.select("src"))) == set(ids(new.by_dst.select("src")))


def test_patches_are_the_whole_graph_weighed_anew(chain, spark):
    g, _, batch, new, _ = chain
    again = snapshot.prepare(snapshot.apply_batch(g.edges, batch), g.vertices)
    rows = lambda df: {(r["src"], r["dst"]): round(r["w"], 12) for r in df.select("src", "dst", "w").collect()}
    assert rows(new.edges_w) == rows(new.by_dst) == rows(again.edges_w) and new.m == new.edges.count()
    many = snapshot.materialised(new)
    assert rows(many.edges_w) == rows(again.edges_w) and many.patches == 0


def test_positions_and_batches(spark):
    v = spark.createDataFrame([(f"v{k:04d}",) for k in range(777)], "id string")
    got = sorted(tuple(r) for r in batches.dense_positions(v, 7).collect())
    assert got == [(f"v{k:04d}", k) for k in range(777)]
    g = snapshot.materialised(snapshot.prepare(synthetic(spark, "uniform", 200, m=1500)))
    for kind in ("ins", "del", "mix"):
        b = batches.generate(kind, g, 100)
        ins, dels = b.ins.count(), b.dels.count()
        assert dels == {"ins": 0, "del": 100, "mix": 20}[kind] and ins <= {"ins": 100, "del": 0, "mix": 80}[kind] and ins >= 0.9 * {"ins": 100, "del": 0, "mix": 80}[kind]
        assert b.ins.join(g.edges, ["src", "dst"]).count() == 0 and b.dels.join(g.edges, ["src", "dst"], "left_anti").count() == 0
    assert batches.generate("del", g, 1).dels.count() == 1
    with pytest.raises(ValueError, match="kind"):
        batches.generate("x", g, 1)


def test_draws_are_even(spark):
    positions = spark.range(1000).selectExpr("id AS pos", "id")
    pairs = [tuple(r) for r in batches.random_inserts(positions, 1000, 20_000, 5).collect()]
    assert len(pairs) > 0.97 * 20_000
    for side in (0, 1):
        count = [0] * 10
        for p in pairs:
            count[p[side] // 100] += 1
        assert all(abs(c - len(pairs) / 10) < 5 * (len(pairs) / 10) ** 0.5 for c in count)
    cells = [0] * 100
    for x, y in pairs:
        cells[x // 100 * 10 + y // 100] += 1
    assert sum((c - len(pairs) / 100) ** 2 / (len(pairs) / 100) for c in cells) < 160  # chi-square of 99


def test_summary_of_studies():
    from rankflow.plans import studies

    rows = [{"workload": "w", "method": m, "seconds": s, "vertex_updates": u, "edges_read": u} for m, s, u in (("cold", 4.0, 100), ("cold", 9.0, 400), ("frontier", 2.0, 10), ("frontier", 2.0, 40))]
    got = {r["method"]: r for r in studies.summary(rows, "workload")}
    assert got["cold"]["seconds"] == pytest.approx(6.0) and got["cold"]["seconds_over_frontier"] == 3.0 and got["cold"]["vertex_updates_over_frontier"] == 10.0


def test_measures(spark):
    df = spark.createDataFrame([("a", "x", 1.0), ("a", "y", 4.0), ("b", "x", 10.0), ("b", "y", 10.0)], "method string, g string, seconds double")
    assert measures.speedup(df, "seconds", "a").first()["speedup"] == pytest.approx(5.0)
    r = spark.createDataFrame([(k, x) for k, x in enumerate([0.1, 0.2, 0.3, 0.4])], "id bigint, rank double")
    assert measures.gini(r, 8).first()[0] == pytest.approx(0.25)
    assert measures.l1(r, r.where("id < 3")).first()[0] == pytest.approx(0.4)
    assert measures.topk_overlap(r, r, 2).first()[0] == 1.0


def test_sources(spark, tmp_path):
    (tmp_path / "e.tsv").write_text("# c\n1\t2\n2\t3\n")
    assert {tuple(r) for r in read_edge_list(spark, str(tmp_path / "e.tsv")).collect()} == {(1, 2), (2, 3)}
    (tmp_path / "m.mtx").write_text("%%MatrixMarket matrix coordinate pattern symmetric\n% c\n3 3 2\n1 2\n3 2\n")
    assert {tuple(r) for r in read_matrix_market(spark, str(tmp_path / "m.mtx")).collect()} == {(1, 2), (2, 1), (3, 2), (2, 3)}
    (tmp_path / "w.mtx").write_text("%%MatrixMarket matrix coordinate real general\n% c\n3 3 2\n3 3 2\n1 2 5\n")
    assert {tuple(r) for r in read_matrix_market(spark, str(tmp_path / "w.mtx")).collect()} == {(3, 3), (1, 2)}
    assert {tuple(r) for r in synthetic(spark, "star", 4).collect()} == {(1, 0), (2, 0), (3, 0)}
    assert synthetic(spark, "skewed", 50, m=300).count() == 300


def test_small_graphs(spark):
    e = spark.createDataFrame([(1, 0, 1), (2, 5, 6), (2, 6, 7)], "graph_id bigint, src bigint, dst bigint")
    got = {(r[0], r[1]): r[2] for r in udfs.rank_small_graphs(e).collect()}
    assert got[1, 0] == pytest.approx(0.075 / 0.575, abs=1e-8) and len(got) == 5


def test_plans_have_no_cartesian_product(chain):
    g, before, batch, new, _ = chain
    for df in (kernel.pull_step(g, before, 0.85), mark.initial(new, batch), measures.l1(before, before)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan and "NestedLoop" not in plan
    assert "SinglePartition" not in kernel.pull_step(g, before, 0.85)._jdf.queryExecution().executedPlan().toString()


def test_every_window_has_its_batch(spark):
    from datetime import datetime, timedelta

    day = lambda d, h=0: datetime(2031, 3, d, h)
    rows = [(1, 2, day(1, 5)), (2, 3, day(2)), (3, 4, day(2, 23)), (4, 5, day(4, 1)), (5, 6, day(9, 7))]
    timed = spark.createDataFrame(rows, "src bigint, dst bigint, ts timestamp_ntz")
    times = spark.createDataFrame([(day(1, 4),), (day(9, 9),)], "ts timestamp_ntz")
    for width, keep in ((timedelta(days=1), timedelta(days=7)), (timedelta(hours=6), timedelta(hours=45))):
        count = (day(9, 9) - day(1)) // width + 1
        want = {(k, *r) for k, b in enumerate(batches.sliding(timed, day(1), width, keep, count)) for r in b.signed().select("src", "dst", "op").collect()} if width.days else None
        got = [tuple(r) for r in batches.slide(timed, times, width, keep).collect()]
        plain = {((t - day(1)) // width, s, d, "+") for s, d, t in rows} | {(k, s, d, "-") for s, d, t in rows if (k := (t + keep - day(1)) // width) < count}
        assert set(got) == plain and len(got) == len(plain) and want in (None, plain)


def test_reach_on_long_chains_and_any_graph(spark):
    import random

    random.seed(4)
    names = random.sample(range(1000), 60)
    pairs = [(a, b) for x, y in zip(names, names[1:], strict=False) if {x, y} != {names[29], names[30]} for a, b in ((x, y), (y, x))]
    pairs += [(names[29], names[30]), (names[59], 2000), (2000, 2001), (2001, 2000), (2001, 2002), (3000, names[0]), (3001, 3001), (3002, 3000), (3003, 3004), (3004, 3005), (3005, 3003)]
    out = {}
    for a, b in pairs:
        out.setdefault(a, []).append(b)
    for start in ({names[40], 3004}, {2002, 3000, 3001}):
        seen, front = set(), start
        while front := {b for a in front for b in out.get(a, [])} - seen:
            seen |= front
        rows = mark.reachable(edges(spark, *pairs), spark.createDataFrame([(v,) for v in start], "id bigint")).collect()
        assert {r[0] for r in rows} == seen and len(rows) == len(seen)


def test_reach_queries_are_on_the_main_graph():
    from rankflow.plans.queries import MAIN, registry

    known = registry().sql
    for name in ("reach_set_ins", "reach_set_del", "reach_set_mix", "reach_k5_ins", "reach_k5_del", "reach_k5_mix"):
        assert graphs.SQL[MAIN] in known[name] and graphs.SQL["page_links"] in known[name.replace("_ins", "_pages_ins").replace("_del", "_pages_del").replace("_mix", "_pages_mix")]
