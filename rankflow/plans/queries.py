"""Registered queries of the rank engine, each with its SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable
from datetime import timedelta

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rankflow import graphs
from rankflow.functions import measures
from rankflow.model import Batch, Graph, Params
from rankflow.operators import batches, kernel, mark, methods, snapshot
from rankflow.plans import oracle as o
from rankflow.storage import written

Query = Callable[[SparkSession, str], DataFrame]
#: Edges in a batch, rounds before it, and the frontier tolerance of the queries.
SIZE, BEFORE, TAU_F = 40, 5, 1e-9
MAIN = "order_chain"
#: Graphs of the reachability queries, by what their names have more: long chains, and links of few hops.
REACHED = {"": MAIN, "pages_": "page_links"}


def p12() -> Column:
    return F.round(F.col("rank") * 1e12).cast("long").alias("rank_p12")


def fixed(k: int, **other) -> Params:
    """Exactly ``k`` rounds."""
    return Params(max_iter=k, stop=False, tau_f=TAU_F, write_every=min(k, 10)).but(**other)


def ready(spark: SparkSession, sf_dir: str, name: str, dead: str = "selfloop") -> Graph:
    return snapshot.materialised(snapshot.prepare(graphs.BUILDERS[name](spark, sf_dir), dead=dead))


def changed(graph: Graph, kind: str, size: int = SIZE) -> tuple[Batch, Graph]:
    drawn = batches.generate(kind, graph, size)
    batch = Batch(written(drawn.ins, "ins"), written(drawn.dels, "dels"))
    return batch, snapshot.after(graph, batch)


class Registry:
    def __init__(self) -> None:
        self.queries: dict[str, Query] = {}
        self.sql: dict[str, str] = {}

    def add(self, name: str, query: Query, sql: str | None = None) -> None:
        self.queries[name] = query
        if sql is not None:
            self.sql[name] = sql


def _graphs(r: Registry) -> None:
    for name in graphs.SQL:
        build = graphs.turns if name == "turns" else graphs.BUILDERS[name]
        r.add(f"graph_{name}", build, graphs.SQL[name])
    r.add("graph_near_vecs", graphs.near_vecs, graphs.NEAR_SQL)

    def stats(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = None
        for name in ("part_flow", "order_chain", "page_links", "host_paths", "nation_trade"):
            row = measures.graph_stats(snapshot.prepare(graphs.BUILDERS[name](spark, sf_dir))).select(F.lit(name).alias("graph"), "vertices", "edges", F.round("avg_degree", 6).alias("avg_degree"))
            out = row if out is None else out.union(row)
        return out

    one = lambda n: "SELECT * FROM (" + o.select(o.graph(n), f"SELECT '{n}' AS graph, (SELECT count(*) FROM v) AS vertices, (SELECT count(*) FROM g) AS edges, round((SELECT count(*) FROM g) / (SELECT n FROM nn), 6) AS avg_degree") + ")"
    r.add("graph_stats_all", stats, " UNION ALL ".join(map(one, ("part_flow", "order_chain", "page_links", "host_paths", "nation_trade"))))
    raw = lambda s, d: snapshot.prepare(graphs.page_links(s, d), dead="none")
    r.add("dead_ends_pages", lambda s, d: snapshot.dead_ends(raw(s, d).edges, raw(s, d).vertices), o.select(o.graph("page_links", "none"), "SELECT id FROM v WHERE id NOT IN (SELECT src FROM e)"))
    whole = lambda s, d: snapshot.prepare(graphs.part_flow(s, d))
    r.add("self_loops", lambda s, d: whole(s, d).edges, o.select(o.graph("part_flow"), "SELECT src, dst FROM g"))
    r.add("out_degrees", lambda s, d: snapshot.out_degrees(whole(s, d).edges), o.select(o.graph("part_flow"), "SELECT src, count(*) AS degree FROM g GROUP BY src"))
    weight = lambda: F.round(F.col("w") * 1e12).cast("long").alias("w_p12")
    r.add("edge_weights", lambda s, d: whole(s, d).edges_w.select("src", "dst", weight()), o.select(o.graph("part_flow"), "SELECT src, dst, CAST(round(w * 1e12) AS BIGINT) AS w_p12 FROM w"))
    r.add("symmetrize", lambda s, d: snapshot.symmetrize(graphs.part_flow(s, d)), o.select(o.graph("part_flow"), "SELECT src, dst FROM e UNION SELECT dst, src FROM e"))


def _full(r: Registry) -> None:
    def cold(name: str, k: int, dead: str = "selfloop", **other) -> Query:
        return lambda s, d: methods.cold(ready(s, d, name, dead), fixed(k, dead_ends=dead, **other)).ranks.select("id", p12())

    def sql(name: str, k: int, dead: str = "selfloop", lost: str = "") -> str:
        return o.select([*o.graph(name, dead), o.uniform(), *o.steps(k, "w", "r0", "a", lost)], f"SELECT id, {o.P12} FROM a{k}")

    r.add("pull_step_once", lambda s, d: _once(ready(s, d, MAIN)), sql(MAIN, 1))
    for name in ("part_flow", "order_chain", "nation_trade", "gram_path", "host_paths"):
        r.add(f"cold_k20_{name}", cold(name, 20), sql(name, 20))
    r.add("cold_k20_cust_supp", cold("cust_supp", 20), sql("cust_supp", 20))
    r.add("cold_teleport_k10_pages", cold("page_links", 10, "teleport"), sql("page_links", 10, "teleport", "g"))
    r.add("cold_none_k10_pages", cold("page_links", 10, "none"), sql("page_links", 10, "none"))
    r.add("cold_converged_nation_trade", lambda s, d: methods.cold(ready(s, d, "nation_trade"), Params(write_every=2)).ranks.select("id", F.round(F.col("rank") * 1e8).cast("long").alias("rank_p8")), o.select([*o.graph("nation_trade"), o.uniform(), *o.steps(40, "w", "r0", "a")], "SELECT id, CAST(round(rank * 1e8) AS BIGINT) AS rank_p8 FROM a40"))
    r.add("cold_local_nation_trade", lambda s, d: methods.cold(ready(s, d, "nation_trade"), Params(discipline="local", blocks=4, tau=1e-12)).ranks.select("id", F.round(F.col("rank") * 1e8).cast("long").alias("rank_p8")), r.sql["cold_converged_nation_trade"])
    r.add("reference_nation_trade", lambda s, d: methods.reference(ready(s, d, "nation_trade"), 60, Params(write_every=10)).ranks.select("id", F.round(F.col("rank") * 1e8).cast("long").alias("rank_p8")), r.sql["cold_converged_nation_trade"])


def _once(graph: Graph) -> DataFrame:
    return kernel.pull_step(graph, methods.uniform(graph), 0.85).select("id", p12())


def _batches(r: Registry) -> None:
    for kind in ("ins", "del", "mix"):
        parts = [*o.graph(MAIN), *o.batch(kind, SIZE)]
        r.add(f"batch_{kind}", lambda s, d, kind=kind: batches.generate(kind, ready(s, d, MAIN), SIZE).signed(), o.select(parts, "SELECT src, dst, '+' AS op FROM ins UNION ALL SELECT src, dst, '-' FROM dels"))
        r.add(f"mark_initial_{kind}", lambda s, d, kind=kind: _initial(ready(s, d, MAIN), kind), o.select([*parts, o.INITIAL], "SELECT id FROM m0"))
        for more, name in REACHED.items():
            r.add(f"reach_set_{more}{kind}", lambda s, d, kind=kind, name=name: _reached(ready(s, d, name), kind), o.select([*o.graph(name), *o.batch(kind, SIZE), o.REACHED], "SELECT id FROM rs", recursive=True))
    def tenth(s: SparkSession, d: str) -> DataFrame:
        g = ready(s, d, MAIN)
        return batches.generate("mix", g, round(0.1 * g.edges.count())).signed()

    r.add("batch_tenth_mix", tenth, o.select([*o.graph(MAIN), *o.batch("mix", "(SELECT CAST(round(0.1 * count(*)) AS BIGINT) FROM g)")], "SELECT src, dst, '+' AS op FROM ins UNION ALL SELECT src, dst, '-' FROM dels"))
    pages = [*o.graph("page_links"), *o.batch("mix", SIZE)]
    walk = lambda edges, name: f"{name} AS (SELECT dst AS id FROM {edges} WHERE src IN (SELECT id FROM so) UNION SELECT b.dst FROM {name} JOIN {edges} b ON b.src = {name}.id)"
    for which, sql in (("current", o.select([*pages, walk("g2", "rs")], "SELECT id FROM rs", recursive=True)), ("either", o.select([*pages, walk("g", "ro"), walk("g2", "rs")], "SELECT id FROM ro UNION SELECT id FROM rs", recursive=True))):
        r.add(f"reach_set_{which}_pages_mix", lambda s, d, which=which: _reached(ready(s, d, "page_links"), "mix", which), sql)
    mix = [*o.graph(MAIN), *o.batch("mix", SIZE)]

    def applied(s: SparkSession, d: str) -> DataFrame:
        g = ready(s, d, MAIN)
        return snapshot.apply_batch(g.edges, batches.generate("mix", g, SIZE), g.vertices)

    def differs(s: SparkSession, d: str) -> DataFrame:
        g = ready(s, d, MAIN)
        return snapshot.diff(g.edges, changed(g, "mix")[1].edges).signed()

    def degrees(s: SparkSession, d: str) -> DataFrame:
        g = ready(s, d, MAIN)
        return snapshot.update_degrees(snapshot.out_degrees(g.edges), batches.generate("mix", g, SIZE))

    r.add("apply_batch", applied, o.select(mix, "SELECT src, dst FROM g2"))
    r.add("snapshot_diff", differs, r.sql["batch_mix"])
    r.add("degree_upkeep", degrees, o.select(mix, "SELECT src, count(*) AS degree FROM g2 GROUP BY src"))

    def normal(s: SparkSession, d: str) -> DataFrame:
        g = ready(s, d, "nation_trade")
        asked = g.edges.where("src < 5")
        raw = Batch(asked.union(asked).union(g.edges.selectExpr("src + 100 AS src", "dst").where("src < 107")), g.edges.where("src >= 3 AND src < 8"))
        return snapshot.normalize(raw, g.edges).signed()

    r.add("batch_normalize", normal, o.select(o.graph("nation_trade"), "SELECT DISTINCT src + 100 AS src, dst, '+' AS op FROM g WHERE src + 100 < 107 UNION ALL SELECT src, dst, '-' FROM g WHERE src >= 5 AND src < 8 AND src <> dst"))
    r.add("temporal_batches_day", lambda s, d: batches.windows(graphs.touch(s, d)), f"SELECT date_trunc('day', ts) AS window_start, count(*) AS edges FROM ({graphs.SQL['touch']}) GROUP BY 1")

    def slid(s: SparkSession, d: str) -> DataFrame:
        return batches.slide(graphs.handoff(s, d), graphs.table(s, d, "events"), timedelta(days=1), timedelta(days=7))

    days = "SELECT date_diff('day', low, CAST(ts AS DATE)) AS day, src, dst, date_diff('day', low, high) AS last FROM h, (SELECT CAST(min(ts) AS DATE) AS low, CAST(max(ts) AS DATE) AS high FROM events)"
    r.add("temporal_sliding", slid, f"WITH h AS ({graphs.SQL['handoff']}), t AS ({days}) SELECT CAST(day AS INTEGER) AS batch, src, dst, '+' AS op FROM t UNION ALL SELECT CAST(day + 7 AS INTEGER), src, dst, '-' FROM t WHERE day + 7 <= last")


def _initial(graph: Graph, kind: str) -> DataFrame:
    batch, new = changed(graph, kind)
    return mark.initial(new, batch)


def _reached(graph: Graph, kind: str, snapshots: str = "union") -> DataFrame:
    batch, new = changed(graph, kind)
    return mark.reach_set(graph, new, batch, snapshots)


def _updates(r: Registry) -> None:
    def update(method: str, kind: str, k: int, name: str = MAIN, with_marks: bool = True, **other) -> Query:
        def query(s: SparkSession, d: str) -> DataFrame:
            old = ready(s, d, name)
            batch, new = changed(old, kind)
            before = methods.cold(old, fixed(BEFORE)).ranks
            out = methods.run(method, old, new, batch, before, fixed(k, **other))
            ranks = out.ranks.select("id", p12())
            return ranks.join(out.affected.select("id", F.lit(True).alias("affected")), "id", "left").fillna(False, ["affected"]) if with_marks else ranks

        return query

    def start(kind: str, name: str = MAIN) -> list[str]:
        return [*o.graph(name), *o.batch(kind, SIZE), o.uniform(), *o.steps(BEFORE, "w", "r0", "a")]

    def frontier(kind: str, k: int, tau_f: float = TAU_F, blocks: int = 1, name: str = MAIN) -> str:
        parts = [*start(kind, name), o.INITIAL, *o.restricted(k, f"a{BEFORE}", "m0", True, tau_f, blocks)]
        return o.select(parts, f"SELECT id, {o.P12}, id IN (SELECT id FROM m{k * blocks}) AS affected FROM x{k * blocks}")

    for kind in ("ins", "del", "mix"):
        r.add(f"warm_k5_{kind}", update("warm", kind, 5, with_marks=False), o.select([*start(kind), *o.steps(5, "w2", f"a{BEFORE}", "b")], f"SELECT id, {o.P12} FROM b5"))
        for more, name in REACHED.items():
            parts = [*start(kind, name), o.REACHED, "ms AS MATERIALIZED (SELECT DISTINCT id FROM rs)", *o.restricted(5, f"a{BEFORE}", "ms", False, 0.0)]
            r.add(f"reach_k5_{more}{kind}", update("reach", kind, 5, name), o.select(parts, f"SELECT id, {o.P12}, id IN (SELECT id FROM ms) AS affected FROM x5", recursive=True))
        for k in (1, 2, 5):
            r.add(f"frontier_k{k}_{kind}", update("frontier", kind, k), frontier(kind, k))
    r.add("frontier_never_expand", update("frontier", "mix", 3, tau_f=1e300), frontier("mix", 3, 1e300))
    # ranks only: whether a change of none at all is none to the last bit depends on the order of sums
    r.add("frontier_tau_zero", update("frontier", "mix", 3, with_marks=False, tau_f=0.0), o.select([*start("mix"), o.INITIAL, *o.restricted(3, f"a{BEFORE}", "m0", True, 0.0)], f"SELECT id, {o.P12} FROM x3"))
    r.add("frontier_blocked_b2", update("frontier", "mix", 3, discipline="blocked", blocks=2), frontier("mix", 3, blocks=2))
    r.add("frontier_k5_part_flow", update("frontier", "ins", 5, "part_flow"), frontier("ins", 5, name="part_flow"))
    r.add("frontier_k5_nation_trade", update("frontier", "mix", 5, "nation_trade"), frontier("mix", 5, name="nation_trade"))
    r.add("warm_blocked_b2", lambda s, d: _warm_blocked(s, d), o.select([*start("mix", "nation_trade"), *o.restricted(3, f"a{BEFORE}", "v", False, 0.0, 2)], f"SELECT id, {o.P12} FROM x6"))

    def share(method: str, name: str) -> Query:
        def query(s: SparkSession, d: str) -> DataFrame:
            old = ready(s, d, name)
            batch, new = changed(old, "mix")
            out = methods.run(method, old, new, batch, methods.cold(old, fixed(BEFORE)).ranks, fixed(5))
            return s.range(1).select(F.round(F.lit(100.0 * measures.affected_fraction(out, new.n)), 9).alias("affected_pct"))

        return query

    final = "SELECT round(100.0 * count(*) / (SELECT n FROM nn), 9) AS affected_pct FROM "
    r.add("affected_final_frontier", share("frontier", MAIN), o.select([*start("mix"), o.INITIAL, *o.restricted(5, f"a{BEFORE}", "m0", True, TAU_F)], final + "m5"))
    r.add("affected_final_reach_pages", share("reach", "page_links"), o.select([*start("mix", "page_links"), o.REACHED], final + "(SELECT DISTINCT id FROM rs)", recursive=True))

    def converged(method: str) -> Query:
        def query(s: SparkSession, d: str) -> DataFrame:
            old = ready(s, d, "nation_trade")
            batch, new = changed(old, "mix")
            out = methods.run(method, old, new, batch, methods.cold(old, fixed(BEFORE)).ranks, Params(tau=1e-13, tau_f=0.0))
            return out.ranks.select("id", F.round(F.col("rank") * 1e8).cast("long").alias("rank_p8"))

        return query

    for method in ("warm", "reach", "frontier"):
        r.add(f"{method}_converged_nation_trade", converged(method), o.select([*start("mix", "nation_trade"), *o.steps(60, "w2", f"a{BEFORE}", "b")], "SELECT id, CAST(round(rank * 1e8) AS BIGINT) AS rank_p8 FROM b60"))

    def tolerances(s: SparkSession, d: str) -> DataFrame:
        old = ready(s, d, MAIN)
        batch, new = changed(old, "ins")
        before = methods.cold(old, fixed(BEFORE)).ranks
        rows = None
        for tau_f in (1e-6, 1e-7, 1e-8, 1e-9):
            out = methods.frontier(old, new, batch, before, fixed(4, tau_f=tau_f))
            row = out.affected.agg(F.count(F.lit(1)).alias("affected")).select(F.lit(repr(tau_f)).alias("tau_f"), "affected")
            rows = row if rows is None else rows.union(row)
        return rows

    one = lambda t: "SELECT * FROM (" + o.select([*start("ins"), o.INITIAL, *o.restricted(4, f"a{BEFORE}", "m0", True, t)], f"SELECT '{t!r}' AS tau_f, count(*) AS affected FROM m4") + ")"
    r.add("frontier_tau_sweep", tolerances, " UNION ALL ".join(map(one, (1e-6, 1e-7, 1e-8, 1e-9))))

    def grown(s: SparkSession, d: str) -> DataFrame:
        g = ready(s, d, "nation_trade")
        ranks = methods.cold(g, fixed(20)).ranks
        added = s.createDataFrame([(1000,), (1001,)], "id bigint")
        return snapshot.rescale(ranks, g.n, g.n + 2, added).select("id", p12())

    scaled = [*o.graph("nation_trade"), o.uniform(), *o.steps(20, "w", "r0", "a")]
    r.add("vertex_add_rescale", grown, o.select(scaled, f"SELECT id, {o.P12} FROM (SELECT id, rank * (n / (n + 2)) AS rank FROM a20, nn UNION ALL SELECT x, 1 / (n + 2) FROM nn, (VALUES (CAST(1000 AS BIGINT)), (1001)) AS t(x))"))


def _warm_blocked(spark: SparkSession, sf_dir: str) -> DataFrame:
    old = ready(spark, sf_dir, "nation_trade")
    batch, new = changed(old, "mix")
    before = methods.cold(old, fixed(BEFORE)).ranks
    return methods.warm(new, before, fixed(3, discipline="blocked", blocks=2)).ranks.select("id", p12())


def _measures(r: Registry) -> None:
    name = "nation_trade"
    two = [*o.graph(name), o.uniform(), *o.steps(6, "w", "r0", "a")]

    def ranks(s: SparkSession, d: str, k: int) -> tuple[Graph, DataFrame]:
        g = ready(s, d, name)
        return g, methods.cold(g, fixed(k)).ranks

    def scaled(c: str, digits: int = 12) -> Column:
        return F.round(F.col(c) * 10.0**digits).cast("long").alias(f"{c}_p12")

    r.add("l1_error", lambda s, d: measures.l1(ranks(s, d, 3)[1], ranks(s, d, 6)[1]).select(scaled("l1")), o.select(two, "SELECT CAST(round(sum(abs(x.rank - y.rank)) * 1e12) AS BIGINT) AS l1_p12 FROM a3 x JOIN a6 y USING (id)"))
    r.add("linf_delta", lambda s, d: measures.linf(ranks(s, d, 3)[1], ranks(s, d, 6)[1]).select(scaled("linf")), o.select(two, "SELECT CAST(round(max(abs(x.rank - y.rank)) * 1e12) AS BIGINT) AS linf_p12 FROM a3 x JOIN a6 y USING (id)"))
    r.add("rank_mass", lambda s, d: measures.mass(ranks(s, d, 6)[1]).select(scaled("drift")), o.select(two, "SELECT CAST(round(abs(sum(rank) - 1) * 1e12) AS BIGINT) AS drift_p12 FROM a6"))
    r.add("residual_l1", lambda s, d: measures.residual(*ranks(s, d, 3)).select(scaled("residual"), scaled("certificate")), o.select(two, f"SELECT CAST(round(x * 1e12) AS BIGINT) AS residual_p12, CAST(round(x / {1 - 0.85} * 1e12) AS BIGINT) AS certificate_p12 FROM (SELECT sum(abs(x.rank - y.rank)) AS x FROM a3 x JOIN a4 y USING (id))"))
    r.add("topk_overlap", lambda s, d: measures.topk_overlap(*(ranks(s, d, k)[1].select("id", F.round("rank", 12).alias("rank")) for k in (1, 6)), 5), o.select(two, "SELECT count(*) / CAST(5 AS DOUBLE) AS overlap FROM (SELECT id FROM a1 ORDER BY round(rank, 12) DESC, id LIMIT 5) JOIN (SELECT id FROM a6 ORDER BY round(rank, 12) DESC, id LIMIT 5) USING (id)"))
    order = "SELECT id, row_number() OVER (ORDER BY round(rank, 12) DESC, id) AS i FROM"
    r.add("rank_correlation", lambda s, d: measures.rank_correlation(*(ranks(s, d, k)[1] for k in (1, 6))).select(F.round("correlation", 9).alias("correlation")), o.select(two, f"SELECT round(corr(CAST(x.i AS DOUBLE), CAST(y.i AS DOUBLE)), 9) AS correlation FROM ({order} a1) x JOIN ({order} a6) y USING (id)"))
    r.add("gini_rank", lambda s, d: measures.gini(ranks(s, d, 6)[1]).select(F.round(F.col("gini") * 1e9).cast("long").alias("gini_p9")), o.select(two, "SELECT CAST(round((2 * sum(i * rank) / (count(*) * sum(rank)) - (count(*) + 1) / CAST(count(*) AS DOUBLE)) * 1e9) AS BIGINT) AS gini_p9 FROM (SELECT rank, row_number() OVER (ORDER BY rank) AS i FROM a6)"))

    def share(s: SparkSession, d: str) -> DataFrame:
        g = ready(s, d, MAIN)
        batch, new = changed(g, "ins")
        found = mark.initial(new, batch).agg(F.count(F.lit(1)).alias("k"))
        return found.select(F.round(100.0 * F.col("k") / g.n, 9).alias("affected_pct"))

    r.add("affected_pct", share, o.select([*o.graph(MAIN), *o.batch("ins", SIZE), o.INITIAL], "SELECT round(100.0 * count(*) / (SELECT n FROM nn), 9) AS affected_pct FROM m0"))
    prices = lambda s, d: measures.geomean(graphs.table(s, d, "part"), "p_retailprice", "p_brand").select("p_brand", F.round("p_retailprice", 6).alias("mean"))
    r.add("geomean_values", prices, "SELECT p_brand, round(exp(avg(ln(p_retailprice))), 6) AS mean FROM part GROUP BY 1")


def _reports(r: Registry) -> None:
    parts = [*o.graph("part_flow"), o.uniform(), *o.steps(10, "w", "r0", "a")]
    named = lambda s, d: methods.cold(ready(s, d, "part_flow"), fixed(10)).ranks.join(graphs.table(s, d, "part").select(F.col("p_partkey").alias("id"), "p_brand", "p_type"), "id")
    r.add("top_parts_by_rank", lambda s, d: measures.top_k(named(s, d).withColumn("rank", F.round("rank", 15)), 20).select("id", "p_brand"), o.select(parts, "SELECT id, p_brand FROM a10 JOIN part ON p_partkey = id ORDER BY round(rank, 15) DESC, id LIMIT 20"))
    total = lambda: F.round(F.sum("rank") * 1e9).cast("long").alias("total_p9")
    r.add("rank_by_brand_rollup", lambda s, d: named(s, d).rollup("p_brand", "p_type").agg(total()), o.select(parts, "SELECT p_brand, p_type, CAST(round(sum(rank) * 1e9) AS BIGINT) AS total_p9 FROM a10 JOIN part ON p_partkey = id GROUP BY ROLLUP (p_brand, p_type)"))
    r.add("rank_brand_cube", lambda s, d: named(s, d).cube("p_brand", "p_type").agg(total()), o.select(parts, "SELECT p_brand, p_type, CAST(round(sum(rank) * 1e9) AS BIGINT) AS total_p9 FROM a10 JOIN part ON p_partkey = id GROUP BY CUBE (p_brand, p_type)"))


def _functions(r: Registry) -> None:
    from rankflow.functions import udfs

    r.add("small_graph_ranks", lambda s, d: udfs.rank_small_graphs(graphs.turns(s, d)).select("graph_id", "id", F.round(F.col("rank") * 1e6).cast("long").alias("rank_p6")), o.select(o.small_graphs(graphs.SQL["turns"], 240), "SELECT graph_id, id, CAST(round(rank * 1e6) AS BIGINT) AS rank_p6 FROM y240"))
    r.add("synthetic_ring", graphs.ring, graphs.RING_SQL)

    def cosines(s: SparkSession, d: str) -> DataFrame:
        v = graphs.table(s, d, "embeddings").select("vec_id", "embedding")
        pairs = v.join(v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other")), "vec_id")
        return pairs.select("vec_id", F.round(udfs.cosine("embedding", "other"), 6).alias("cosine"))

    r.add("cosine_neighbours", cosines, "SELECT a.vec_id, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
    urls = lambda s, d: graphs.table(s, d, "pages").select("page_id", udfs.canonical_url("url").alias("url"))
    host = "regexp_replace(lower(split_part(u, '/', 3)), CASE WHEN starts_with(lower(u), 'https:') THEN ':443$' ELSE ':80$' END, '')"
    r.add("canonical_urls", urls, f"SELECT page_id, lower(split_part(u, '//', 1)) || '//' || {host} || regexp_replace(regexp_replace(u, '^[^/]*//[^/?]*', ''), '/+([?]|$)', '\\1') AS url FROM (SELECT page_id, regexp_replace(url, '#.*$', '') AS u FROM pages)")


def registry() -> Registry:
    from rankflow.plans import relational, streams, surface

    r = Registry()
    for part in (_graphs, _full, _batches, _updates, _measures, _reports, _functions, relational.add, surface.add, streams.add):
        part(r)
    return r
