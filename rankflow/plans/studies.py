"""The experiment workloads: which method wins, and how each measure moves with each parameter.

Every runner yields rows ``workload, graph, kind, fraction, batch_edges, method,
discipline, tau, tau_f, seconds, iterations, vertex_updates, affected_pct,
l1_error``.  Seconds cover marking and the test for convergence; inputs are
tables written before.  On small tables they are ruled by the cost of jobs, and
vertex updates tell more.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from datetime import datetime, timedelta

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankflow import graphs
from rankflow.functions import measures
from rankflow.model import Batch, Graph, Params, RankResult
from rankflow.operators import batches, methods, snapshot
from rankflow.storage import discard, written

GRAPHS = ("part_flow", "cust_supp", "order_chain", "gram_path", "page_links", "host_paths")
STUDIED = GRAPHS[:4]
#: Sizes of batches as shares of the edges; those that come to the same number of edges are drawn once.
FRACTIONS = (1e-7, 1e-6, 1e-5, 1e-4, 1e-3, 1e-2, 1e-1)
REFERENCE = 500


def opened(spark: SparkSession, sf_dir: str, name: str, params: Params = Params()) -> tuple[Graph, DataFrame]:
    """A graph and its ranks, both as tables."""
    graph = snapshot.materialised(snapshot.prepare(graphs.BUILDERS[name](spark, sf_dir)))
    return graph, methods.kept(methods.cold(graph, params.but(write_every=5)).ranks)


def next_snapshot(graph: Graph, batch: Batch) -> tuple[Batch, Graph, int]:
    batch = Batch(written(batch.ins, "ins"), written(batch.dels, "dels"))
    return batch, snapshot.after(graph, batch), batch.changed().count()


def summary(rows: list[dict], *by: str) -> list[dict]:
    """Geometric means of seconds and of vertex updates by method, and how many times frontier's they are."""
    out = []
    for key in sorted({tuple(str(r.get(b)) for b in by) for r in rows}):
        some = [r for r in rows if tuple(str(r.get(b)) for b in by) == key]
        means = {m: {w: math.exp(sum(math.log(max(r[w], 1e-3)) for r in some if r["method"] == m) / k) for w in ("seconds", "vertex_updates", "edges_read")} for m in methods.METHODS if (k := sum(r["method"] == m for r in some))}
        for m, x in means.items():
            row = dict(zip(by, key, strict=True)) | {"method": m} | {w: round(v, 3) for w, v in x.items()}
            if "frontier" in means:
                row |= {f"{w}_over_frontier": round(v / means["frontier"][w], 2) for w, v in x.items()}
            out.append(row)
    return out


def row(workload: str, graph: str, result: RankResult, n: int, reference: DataFrame | None = None, **about) -> dict:
    p = result.params
    out = {"workload": workload, "graph": graph, "method": result.method, "discipline": p.discipline, "tau": p.tau, "tau_f": p.frontier_tolerance}
    out |= about | {k: round(v, 3) if isinstance(v, float) else v for k, v in measures.work(result).items()}
    out["affected_pct"] = round(100 * measures.affected_fraction(result, n), 4)
    if reference is not None:
        out["l1_error"] = measures.l1(result.ranks, reference).first()[0]
    return out


def update_study(spark: SparkSession, sf_dir: str, kind: str = "ins", names: tuple[str, ...] = GRAPHS, fractions: tuple[float, ...] = FRACTIONS, repeats: int = 3, params: Params = Params(write_every=5)) -> Iterator[dict]:
    """All methods on random batches of one kind, by size: runtime, work, error, share affected."""
    for name in names:
        graph, before = opened(spark, sf_dir, name, params)
        m = graph.edges.count()
        apart = tuple({max(1, round(f * m)): f for f in fractions}.values())
        for fraction, seed, drawn in batches.sweep(graph, kind, apart, repeats):
            batch, new, size = next_snapshot(graph, drawn)
            exact = methods.reference(new, REFERENCE, params.but(write_every=10)).ranks
            for method in methods.METHODS:
                result = methods.run(method, graph, new, batch, before, params)
                yield row(f"update-{kind}", name, result, new.n, exact, kind=kind, fraction=fraction, seed=seed, batch_edges=size)
                discard(result.ranks)


def discipline_study(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = STUDIED, fraction: float = 1e-3) -> Iterator[dict]:
    """Each method in each discipline, on inserts."""
    for name in names:
        graph, before = opened(spark, sf_dir, name)
        batch, new, size = next_snapshot(graph, batches.generate("ins", graph, max(1, round(fraction * graph.edges.count()))))
        for discipline in ("sync", "blocked", "local"):
            for method in methods.METHODS:
                result = methods.run(method, graph, new, batch, before, Params(discipline=discipline))
                yield row("discipline", name, result, new.n, kind="ins", fraction=fraction, batch_edges=size)


def tolerance_study(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = STUDIED, fraction: float = 1e-3, divisors: tuple[float, ...] = (1, 10, 1e2, 1e3, 1e4, 1e5)) -> Iterator[dict]:
    """The frontier method by frontier tolerance, on inserts: a larger one is quicker and less exact."""
    for name in names:
        graph, before = opened(spark, sf_dir, name)
        batch, new, size = next_snapshot(graph, batches.generate("ins", graph, max(1, round(fraction * graph.edges.count()))))
        exact = methods.reference(new, REFERENCE, Params(write_every=10)).ranks
        for divisor in divisors:
            result = methods.frontier(graph, new, batch, before, Params(tau_f_divisor=divisor))
            yield row("tolerance", name, result, new.n, exact, kind="ins", fraction=fraction, batch_edges=size)


def affected_study(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = GRAPHS, fractions: tuple[float, ...] = FRACTIONS) -> Iterator[dict]:
    """Share of vertices marked in the end, reach against frontier, on inserts."""
    for name in names:
        graph, before = opened(spark, sf_dir, name)
        for fraction, seed, drawn in batches.sweep(graph, "ins", fractions, 1):
            batch, new, size = next_snapshot(graph, drawn)
            for method in ("reach", "frontier"):
                yield row("affected", name, methods.run(method, graph, new, batch, before, Params()), new.n, kind="ins", fraction=fraction, seed=seed, batch_edges=size)


def temporal_study(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("handoff", "touch", "cust_supp_timed"), cuts: int = 3, width: timedelta = timedelta(days=1)) -> Iterator[dict]:
    """Edges in the order of their times, with the default frontier tolerance and with looser ones; by day, or by month where orders bring them."""
    for name in names:
        timed = written(getattr(graphs, name)(spark, sf_dir), "timed")
        step = timedelta(days=30) if name == "cust_supp_timed" else width
        start = timed.agg(F.max("ts").cast("date").cast("timestamp_ntz")).first()[0] - (cuts - 1) * step
        vertices = snapshot.vertices_of(timed)
        graph = snapshot.materialised(snapshot.prepare(batches.base_before(timed, start), vertices))
        before = methods.kept(methods.cold(graph, Params(write_every=5)).ranks)
        for day, drawn in enumerate(batches.by_time(timed, start, step, cuts)):
            batch, new, size = next_snapshot(graph, snapshot.normalize(drawn, graph.edges))
            for params in (Params(), Params(tau_f_divisor=100), Params.temporal()):
                for method in methods.METHODS if params == Params() else ("frontier",):
                    yield row("temporal", name, methods.run(method, graph, new, batch, before, params.but(write_every=5)), new.n, kind="time", fraction=None, seed=day, batch_edges=size)
            graph, before = new, methods.kept(methods.warm(new, before, Params(write_every=5)).ranks)


def graph_table(spark: SparkSession, sf_dir: str) -> Iterator[dict]:
    """Vertices, edges with loops, average degree and skew of ranks."""
    for name in GRAPHS:
        graph, ranks = opened(spark, sf_dir, name, Params(tau=1e-8))
        yield {"workload": "graphs", "graph": name} | measures.graph_stats(graph).first().asDict() | {"gini": round(measures.gini(ranks).first()[0], 4)}


def race(spark: SparkSession, sf_dir: str, name: str = "order_chain", size: int = 40, kind: str = "mix", params: Params = Params(write_every=5), only: tuple[str, ...] = methods.METHODS) -> Iterator[dict]:
    """The update alone, by each method, on one graph and batch whose tables are written before."""
    graph, before = opened(spark, sf_dir, name, params)
    batch, new, changed = next_snapshot(graph, batches.generate(kind, graph, size))
    for method in only:
        result, seconds = measures.timed(lambda m=method: methods.run(m, graph, new, batch, before, params))
        yield row("race", name, result, new.n, kind=kind, batch_edges=changed) | {"seconds": round(seconds, 3)}


def scaling_run(spark: SparkSession, sf_dir: str, name: str = "order_chain", fraction: float = 1e-4) -> Iterator[dict]:
    """One frontier and one warm update in this session; ``bench.py scale`` starts sessions of 1, 2 and 4 threads and compares."""
    graph, before = opened(spark, sf_dir, name, Params(tau=1e-8))
    batch, new, size = next_snapshot(graph, batches.generate("ins", graph, max(1, round(fraction * graph.edges.count()))))
    for method in ("warm", "frontier"):
        for _ in range(2):  # the first one warms up
            result = methods.run(method, graph, new, batch, before, Params(tau=1e-8, write_every=5))
        yield row("scaling", name, result, new.n, kind="ins", fraction=fraction, batch_edges=size) | {"threads": spark.sparkContext.defaultParallelism}


WORKLOADS = {
    "graphs": graph_table, "ins": lambda s, d: update_study(s, d, "ins"), "del": lambda s, d: update_study(s, d, "del"), "mix": lambda s, d: update_study(s, d, "mix"),
    "discipline": discipline_study, "tolerance": tolerance_study, "affected": affected_study, "temporal": temporal_study, "scaling": scaling_run, "race": race,
}


def every(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> Iterator[dict]:
    for name in names or WORKLOADS:
        yield from WORKLOADS[name](spark, sf_dir)
