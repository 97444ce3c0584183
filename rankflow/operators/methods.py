"""The four update methods, the reference run, and maintenance over a series of batches.

A restricted method recomputes every marked vertex in every round, and marks are
never taken back.  While marked vertices have few in-edges, at most ``SMALL``, these and
the ranks at their ends are held by the driver: a round is arithmetic on arrays, and
only new marks ask the layouts for their edges.  Beyond that bound a round
reads three tables: the marked vertices, their
in-edges with the previous ranks of the sources, and the last round's results.
The first two only grow: when marks are added, their in-edges are fetched
from the layout by ``dst``, and the ranks of those sources.  Neither all edges nor
all ranks are touched by a round; the ranks of a result are the previous ones
overlaid with the last round's.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from rankflow.model import Batch, Graph, Params, RankResult
from rankflow.operators import kernel, mark, snapshot
from rankflow.storage import appended, bucketed, discard, held, written

METHODS = ("cold", "warm", "reach", "frontier")


def uniform(graph: Graph) -> DataFrame:
    return graph.vertices.select("id", F.lit(1.0 / graph.n).alias("rank"))


def carried(graph: Graph, previous: DataFrame) -> DataFrame:
    """Previous ranks for the vertices of a graph; a vertex without one starts at ``1 / n``."""
    return graph.vertices.join(previous.select("id", "rank"), "id", "left").select("id", F.coalesce("rank", F.lit(1.0 / graph.n)).alias("rank"))


def overlaid(base: DataFrame, moved: DataFrame) -> DataFrame:
    over = moved.select("id", F.col("rank").alias("_new"))
    return base.join(over, "id", "left").select("id", F.coalesce("_new", "rank").alias("rank"))


def block_of(graph: Graph, blocks: int) -> Column:
    own = F.col("id") if isinstance(graph.id_type, IntegralType) else F.xxhash64("id")
    return F.pmod(own, F.lit(blocks))


def _observed(df: DataFrame, tau_f: float, name: str) -> tuple[DataFrame, dict]:
    """The table with ``delta`` written, and its metrics from the same pass."""
    seen = Observation()
    moved = F.col("delta") > tau_f
    fresh = moved & ~F.col("spread") if "spread" in df.columns else moved
    watched = df.observe(seen, F.max("delta").alias("linf"), F.count(F.lit(1)).alias("affected"), F.count_if(moved).alias("movers"), F.count_if(fresh).alias("fresh"))
    out = written(watched, name)
    return out, {k: v or 0 for k, v in seen.get.items()}


def _with_delta(new: DataFrame, old: DataFrame) -> DataFrame:
    return new.join(old.select("id", F.col("rank").alias("_old")), "id", "left").select("id", "rank", F.abs(F.col("rank") - F.coalesce("_old", F.lit(0.0))).alias("delta"))


#: Vertices of a part of the local discipline, about: a part is held by one worker.
PART = 100_000


def _local_sweeps(graph: Graph, ranks: DataFrame, targets: DataFrame | None, params: Params) -> DataFrame:
    """One exchange, then ``inner`` sweeps in each part over its own vertices, with the ranks of others frozen.

    Parts are ``params.blocks``, or more where these would hold over ``PART`` vertices.
    """
    parts = max(params.blocks, -(-graph.n // PART))
    part = F.pmod(F.xxhash64("id"), F.lit(parts))
    of = lambda c: F.pmod(F.xxhash64(c), F.lit(parts))
    edges = graph.edges_w
    goal = graph.vertices if targets is None else targets
    if targets is not None:
        edges = graph.by_dst.join(goal.select(F.col("id").alias("dst")), "dst", "left_semi")
    far = kernel.incoming(edges.where(of("src") != of("dst")), ranks).withColumnRenamed("s", "far")
    flagged = ranks.join(goal.select("id", F.lit(True).alias("goal")), "id", "left").join(far, "id", "left")
    vertices = flagged.select("id", "rank", F.coalesce("goal", F.lit(False)).alias("goal"), F.coalesce("far", F.lit(0.0)).alias("far"), part.alias("part"))
    near = edges.where(of("src") == of("dst")).select("src", "dst", "w", of("dst").alias("part"))
    base, alpha, sweeps = (1.0 - params.alpha) / graph.n, params.alpha, params.inner

    def sweep(e, v):
        import numpy as np
        import pandas as pd

        at = pd.Index(v["id"])
        src, dst = at.get_indexer(e["src"]), at.get_indexer(e["dst"])
        w, rank, goals, fixed = e["w"].to_numpy(), v["rank"].to_numpy().copy(), v["goal"].to_numpy(bool), base + alpha * v["far"].to_numpy()
        for _ in range(sweeps):
            new = fixed + alpha * np.bincount(dst, weights=rank[src] * w, minlength=len(rank))
            rank = np.where(goals, new, rank)
        return v.assign(rank=rank).loc[goals, ["id", "rank"]]

    kind = graph.vertices.schema["id"].dataType.simpleString()
    return near.groupBy("part").cogroup(vertices.groupBy("part")).applyInPandas(sweep, f"id {kind}, rank double")


def _full(graph: Graph, start: DataFrame, params: Params, method: str) -> RankResult:
    """Rounds over all vertices, from given ranks."""
    began = time.monotonic()
    ranks, telemetry, converged, done = start, [], False, 0
    m = graph.edges_w.count() if graph.m is None else graph.m
    while done < params.max_iter and not converged:
        t0 = time.monotonic()
        # a step that reads the ranks more than once is written before the next one
        chained = params.discipline == "sync" and graph.dead_ends != "teleport"
        steps = min(params.write_every, params.max_iter - done) if chained else 1
        old, now = ranks, ranks
        for _ in range(steps):
            old = now
            if params.discipline == "blocked" and params.blocks > 1:
                for b in range(params.blocks):
                    own = graph.vertices.where(block_of(graph, params.blocks) == b)
                    now = overlaid(now, kernel.pull_step(graph, now, params.alpha, own))
            elif params.discipline == "local":
                now = _local_sweeps(graph, now, None, params)
            else:
                now = kernel.pull_step(graph, now, params.alpha)
        table, seen = _observed(_with_delta(now, old), 0.0, f"{method}-ranks")
        discard(ranks if ranks is not start else None)
        ranks, done = table, done + steps
        telemetry.append({"iteration": done, **seen, "affected": seen["affected"] * steps, "in_edges": m * steps, "seconds": time.monotonic() - t0})
        converged = params.stop and seen["linf"] <= params.tau
    return RankResult(held(ranks.select("id", "rank"), ranks), graph.vertices, done, converged, telemetry, 0.0, time.monotonic() - began, method, params)


def kept(ranks: DataFrame) -> DataFrame:
    """Ranks as a table in buckets by id, in which updates look up the few that they need."""
    plain = written(ranks.select("id", "rank"), "ranks")
    out = bucketed(plain, "ranks", "id", snapshot.buckets_of(ranks.sparkSession, plain.count()))
    discard(plain)
    return out


def cold(graph: Graph, params: Params = Params()) -> RankResult:
    """Ranks from scratch: every vertex, from ``1 / n``."""
    return _full(graph, uniform(graph), params, "cold")


def warm(graph: Graph, previous: DataFrame, params: Params = Params()) -> RankResult:
    """Every vertex, from the previous snapshot's ranks."""
    return _full(graph, carried(graph, previous), params, "warm")


def reference(graph: Graph, iters: int = 500, params: Params = Params()) -> RankResult:
    """Ranks for measuring errors: as many rounds as asked for, unless one changes nothing at all."""
    return cold(graph, params.but(tau=0.0, max_iter=iters, discipline="sync", stop=True))


class _Marked:
    """The marked vertices with their previous ranks, and their in-edges with those of the sources, as tables that grow."""

    def __init__(self, graph: Graph, previous: DataFrame):
        self.graph, self.previous = graph, previous
        self.marks: list[DataFrame] = []
        self.edges: list[DataFrame] = []
        self.size = self.in_edges = 0

    def _ranked(self, df: DataFrame, key: str, few: list | None, name: str) -> DataFrame:
        """``df`` with the previous rank of ``key``: only those ranks are looked up."""
        ranks = self.previous.select("id", "rank")
        ranks = ranks.where(F.col("id").isin(few)) if few is not None else ranks
        found = df.join(ranks.select(F.col("id").alias(key), F.col("rank").alias(name)), key, "left")
        return found.withColumn(name, F.coalesce(name, F.lit(1.0 / self.graph.n)))

    def add(self, ids: DataFrame) -> DataFrame:
        """Mark vertices that are not marked yet."""
        fresh = written(ids.select("id"), "fresh")
        few = snapshot.listed(fresh)
        self.marks.append(written(self._ranked(fresh, "id", few, "prev"), "marks"))
        edges = written(snapshot.touching(self.graph.by_dst, "dst", fresh, few, "id").select("src", "dst", "w"), "in-edges")
        sources = edges.select("src").distinct()
        seen = Observation()
        self.edges.append(written(self._ranked(edges, "src", snapshot.listed(sources, "src"), "prev").observe(seen, F.count(F.lit(1)).alias("n")), "in-edges"))
        self.in_edges += seen.get["n"]
        discard(fresh, edges)
        return self.marks[-1]

    @property
    def ids(self) -> DataFrame:
        return appended(self.marks)

    def pulled(self, state: DataFrame | None, params: Params, block: Column | None = None) -> DataFrame:
        """``id, rank, delta, spread`` after a round from ``state``, of all marked vertices or of a block of them.

        ``spread`` tells that the out-neighbours of a vertex were marked before.
        """
        marks, edges = self.ids, appended(self.edges)
        if block is not None:
            marks, edges = marks.where(block), edges.join(marks.where(block).select(F.col("id").alias("dst")), "dst", "left_semi")
        now = F.col("prev")
        if state is not None:
            edges = edges.join(state.select(F.col("id").alias("src"), F.col("rank").alias("now")), "src", "left")
            marks = marks.join(state.select("id", F.col("rank").alias("now"), "spread"), "id", "left")
            now = F.coalesce("now", "prev")
        spread = F.lit(False) if state is None else F.coalesce("spread", F.lit(False))
        sums = edges.groupBy(F.col("dst").alias("id")).agg(F.sum(now * F.col("w")).alias("s"))
        rank = (1.0 - params.alpha) / self.graph.n + params.alpha * F.coalesce("s", F.lit(0.0))
        out = marks.select("id", now.alias("old"), spread.alias("spread")).join(sums, "id", "left")
        return out.select("id", rank.alias("rank"), F.abs(rank - F.col("old")).alias("delta"), "spread")


#: Edges of a graph, or in-edges of marked vertices and those ahead, up to which rounds run on arrays of the driver; vertices fetched at a time; hops ahead.
SMALL, REGION, AHEAD = 1_000_000, 50_000, 2


class _Small:
    """Marked vertices, their in-edges and the ranks at their ends, as arrays; for as long as the edges are few."""

    def __init__(self, graph: Graph, previous: DataFrame, params: Params, grows: bool):
        import numpy as np

        self.np, self.graph, self.previous, self.params = np, graph, previous, params
        self.at: dict = {}
        self.rank = np.zeros(0)
        self.out: dict = {}
        self.ahead = 1 if grows else 0
        self.block, self.spread, self.marked, self.known = np.zeros(0, int), np.zeros(0, bool), np.zeros(0, bool), np.zeros(0, bool)
        self.src, self.dst, self.w, self.delta = np.zeros(0, int), np.zeros(0, int), np.zeros(0), np.zeros(0)

    def _few(self, df: DataFrame, most: int):
        """The rows as an Arrow table, or None if they are over ``most``."""
        out = df.limit(most + 1).toArrow()
        return out if out.num_rows <= most else None

    def _among(self, df: DataFrame, key: str, ids: list) -> DataFrame:
        if len(ids) <= snapshot.LISTED:
            return df.where(F.col(key).isin(ids))
        return df.join(F.broadcast(self._local(ids).withColumnRenamed("id", key)), key, "left_semi")  # at most REGION ids, or ends of SMALL edges

    def _local(self, ids: list) -> DataFrame:
        return self.graph.vertices.sparkSession.createDataFrame([(x,) for x in ids], self.graph.vertices.select("id").schema)

    def _know(self, ids: list, every: bool = False) -> None:
        """Look up the previous ranks of vertices seen for the first time, or of all."""
        fresh = [x for x in dict.fromkeys(ids) if x not in self.at]
        if not fresh:
            return
        np, first = self.np, len(self.at)
        self.at.update(zip(fresh, range(first, first + len(fresh)), strict=True))
        self.rank = np.concatenate((self.rank, np.full(len(fresh), 1.0 / self.graph.n)))
        for name in ("spread", "marked", "known"):
            setattr(self, name, np.concatenate((getattr(self, name), np.zeros(len(fresh), bool))))
        self.block = np.concatenate((self.block, np.zeros(len(fresh), int)))
        blocks = block_of(self.graph, self.params.blocks).cast("int").alias("b")
        ranks = self.previous.select("id", "rank")
        found = (ranks if every else self._among(ranks, "id", fresh)).select("id", "rank", blocks).toArrow()
        found = found.filter([x in self.at for x in found.column("id").to_pylist()])
        k = np.fromiter(map(self.at.__getitem__, found.column("id").to_pylist()), int, found.num_rows)
        self.rank[k], self.block[k] = found.column("rank").to_numpy(), found.column("b").to_numpy()

    def _fetch(self, ids: list, hops: int) -> bool:
        """In- and out-edges of vertices and of what they reach in some hops, or of a whole graph of few edges; False, and nothing done, if these are too many."""
        if self.graph.m is not None and self.graph.m <= SMALL:
            self._take(self.graph.edges_w.select("src", "dst", "w").toArrow(), None, None)
            self.known[:] = True
            return True
        region = self._local(ids)
        loops = self.graph.dead_ends == "selfloop"  # then who is reached in a step holds who was reached before
        for _ in range(hops if loops else min(1, hops)):
            near = self.graph.edges.join(F.broadcast(region), F.col("src") == F.col("id"), "left_semi").select(F.col("dst").alias("id"))
            region = (near if loops else near.union(region)).distinct()
        region = self._few(region, REGION)
        if region is None:
            return False
        region = [x for x in region.column("id").to_pylist() if x not in self.at or not self.known[self.at[x]]]
        room = max(0, SMALL - len(self.w))
        inward = self._few(self._among(self.graph.by_dst.select("src", "dst", "w"), "dst", region), room)
        outward = None if inward is None else self._few(self._among(self.graph.edges, "src", region), SMALL)
        if outward is None:
            return False
        self._take(inward, outward, region)
        self.known[[self.at[x] for x in region]] = True
        return True

    def _take(self, inward, outward, region: list | None) -> None:
        """Keep edges, and the ranks at their ends; without a region, all of the graph's."""
        np = self.np
        src, dst = inward.column("src").to_pylist(), inward.column("dst").to_pylist()
        self._know(src + dst if region is None else region + src, region is None)
        index = lambda some: np.fromiter(map(self.at.__getitem__, some), int, len(some))
        self.src, self.dst = np.concatenate((self.src, index(src))), np.concatenate((self.dst, index(dst)))
        self.w = np.concatenate((self.w, inward.column("w").to_numpy()))
        pairs = zip(src, dst, strict=True) if outward is None else zip(outward.column("src").to_pylist(), outward.column("dst").to_pylist(), strict=True)
        for x, y in pairs:
            self.out.setdefault(x, []).append(y)

    def _ready(self, ids: list) -> bool:
        """Have the edges of vertices at hand; of what lies ahead too, twice as far each time if it is little."""
        if all(x in self.at and self.known[self.at[x]] for x in ids):
            return True
        ahead = self.ahead
        while not self._fetch(ids, ahead):
            if not ahead:
                return False
            ahead //= 2
        self.ahead = min(2 * ahead, AHEAD) if ahead == self.ahead else ahead
        self.ahead = max(1, self.ahead)
        return True

    def add(self, ids: list) -> bool:
        """Mark vertices; False, and nothing done, if their in-edges would be too many."""
        if not self._ready(ids):
            return False
        self.marked[[self.at[x] for x in ids]] = True
        return True

    def round(self, block: int | None, tau_f: float) -> dict:
        """Recompute the marked vertices, or those of a block."""
        np, alpha = self.np, self.params.alpha
        own = self.marked.copy() if block is None else self.marked & (self.block == block)
        sums = np.bincount(self.dst, weights=self.rank[self.src] * self.w, minlength=len(self.rank))
        new = np.where(own, (1.0 - alpha) / self.graph.n + alpha * sums, self.rank)
        delta = np.abs(new - self.rank)
        self.rank, self.delta, self.moved = new, delta, own & (delta > tau_f)
        return {"linf": float(delta.max(initial=0.0)), "affected": int(own.sum()), "movers": int(self.moved.sum())}

    @property
    def in_edges(self) -> int:
        return int(self.marked[self.dst].sum())

    def reached(self) -> list:
        """Unmarked out-neighbours of those that moved and had not before."""
        fresh = self.moved & ~self.spread
        if not fresh.any():
            return []
        names = list(self.at)
        movers = [names[k] for k in self.np.flatnonzero(fresh)]
        self.spread |= fresh
        found = dict.fromkeys(y for x in movers for y in self.out.get(x, ()))
        return [x for x in found if x not in self.at or not self.marked[self.at[x]]]

    def table(self, known: bool = True) -> DataFrame:
        """``id, rank, delta, spread`` of the marked vertices; ``delta`` of those recomputed last.

        Unless ``known``, the spread of these isn't done.
        """
        kind = self.graph.vertices.schema["id"].dataType.simpleString()
        delta = self.np.zeros(len(self.rank))
        delta[: len(self.delta)] = self.delta
        spread = self.spread.copy()
        if not known:
            spread[: len(self.moved)] &= ~self.moved
        rows = [(x, float(self.rank[k]), float(delta[k]), bool(spread[k])) for x, k in self.at.items() if self.marked[k]]
        return written(self.graph.vertices.sparkSession.createDataFrame(rows, f"id {kind}, rank double, delta double, spread boolean"), "moved")


def _restricted(graph: Graph, previous: DataFrame, marks: DataFrame, params: Params, method: str, grows: bool, began: float) -> RankResult:
    if graph.dead_ends == "teleport":
        raise ValueError("restricted methods need dead_ends of selfloop or none")
    first = None
    if params.discipline != "local":
        small = _Small(graph, previous, params, grows)
        first = small._few(marks.select("id"), SMALL)
        first = None if first is None else first.column("id").to_pylist()
        if first is not None and small.add(first):
            return _on_arrays(small, params, method, grows, began)
    return _on_tables(graph, previous, marks, params, method, grows, began)


def _on_arrays(small: _Small, params: Params, method: str, grows: bool, began: float) -> RankResult:
    """Rounds in the driver's memory; if marks outgrow it, the state goes over to tables."""
    seconds_marking, telemetry, converged = time.monotonic() - began, [], False
    blocks = range(params.blocks) if params.discipline == "blocked" and params.blocks > 1 else (None,)
    tau_f = params.frontier_tolerance
    while len(telemetry) < params.max_iter and not converged and small.marked.any():
        t0 = time.monotonic()
        total: dict = {"linf": 0.0, "affected": 0, "movers": 0, "in_edges": small.in_edges}
        for b in blocks:
            seen = small.round(b, tau_f)
            total = {**total, "linf": max(total["linf"], seen["linf"]), "affected": total["affected"] + seen["affected"], "movers": total["movers"] + seen["movers"]}
            more = small.reached() if grows else []
            if more and not small.add(more):
                state = small.table(known=False)
                return _on_tables(small.graph, small.previous, state.select("id"), params, method, grows, began, (state, telemetry, b or 0, total))
        telemetry.append({"iteration": len(telemetry) + 1, **total, "seconds": time.monotonic() - t0})
        converged = params.stop and total["linf"] <= params.tau
    state = small.table()
    ranks = held(overlaid(carried(small.graph, small.previous), state), state)
    return RankResult(ranks, state.select("id"), len(telemetry), converged or not small.marked.any(), telemetry, seconds_marking, time.monotonic() - began, method, params)


def _on_tables(graph: Graph, previous: DataFrame, marks: DataFrame, params: Params, method: str, grows: bool, began: float, resumed: tuple | None = None) -> RankResult:
    """Rounds over tables, from the start or from a state whose last movers have yet to spread."""
    tau_f = params.frontier_tolerance
    moved = (F.col("delta") > tau_f) & ~F.col("spread")
    marked = _Marked(graph, previous)
    marked.size = marked.add(marks).count()
    seconds_marking = time.monotonic() - began
    blocks = params.blocks if params.discipline == "blocked" else 1
    state, telemetry, first, total = resumed or (None, [], 0, None)
    converged = False
    while len(telemetry) < params.max_iter and not converged and marked.size:
        t0 = time.monotonic()
        pending = total is not None
        total = total or {"linf": 0.0, "affected": 0, "movers": 0, "in_edges": marked.in_edges}
        for b in range(first, blocks):
            fresh = pending
            if not pending:
                block = None if blocks == 1 else block_of(graph, blocks) == b
                new = _swept(graph, previous, marked.ids, state, params) if params.discipline == "local" else marked.pulled(state, params, block)
                table, seen = _observed(new, tau_f, f"{method}-moved")
                total = {**total, "linf": max(total["linf"], seen["linf"]), "affected": total["affected"] + seen["affected"], "movers": total["movers"] + seen["movers"]}
                fresh = seen["fresh"]
                if blocks > 1 and state is not None:
                    both = written(state.join(table, "id", "left_anti").select(table.columns).union(table), f"{method}-moved")
                    discard(table, state)
                    table = both
                else:
                    discard(state)
                state = table
            pending = False
            if grows and fresh:
                movers = state.where(moved)
                more = written(mark.out_neighbours(graph.edges, movers, snapshot.listed(movers)).join(marked.ids.select("id"), "id", "left_anti"), "more")
                if found := more.count():
                    marked.add(more)
                    marked.size += found
                discard(more)
            if grows:
                state, last = state.withColumn("spread", F.col("spread") | moved), state
                state.scratch_path = last.scratch_path
        telemetry.append({"iteration": len(telemetry) + 1, **total, "seconds": time.monotonic() - t0})
        converged = params.stop and total["linf"] <= params.tau
        first, total = 0, None
    base = carried(graph, previous)
    ranks = held(base if state is None else overlaid(base, state), state)
    affected = held(marked.ids.select("id"), *marked.marks)
    discard(*marked.edges)
    return RankResult(ranks, affected, len(telemetry), converged or not marked.size, telemetry, seconds_marking, time.monotonic() - began, method, params)


def _swept(graph: Graph, previous: DataFrame, ids: DataFrame, state: DataFrame | None, params: Params) -> DataFrame:
    """A round of the local discipline over the marked vertices; it needs the ranks of all."""
    now = carried(graph, previous)
    now = now if state is None else overlaid(now, state)
    new = _local_sweeps(graph, now, ids.select("id"), params)
    kept = new.withColumn("spread", F.lit(False)) if state is None else new.join(state.select("id", "spread"), "id", "left").withColumn("spread", F.coalesce("spread", F.lit(False)))
    return _with_delta(kept.select("id", "rank"), now).join(kept.select("id", "spread"), "id")


def reach(old: Graph, new: Graph, batch: Batch, previous: DataFrame, params: Params = Params()) -> RankResult:
    """Only what can be reached from the batch's sources, from the previous ranks."""
    began = time.monotonic()
    marks = mark.reach_set(old, new, batch, params.snapshots)
    return _restricted(new, previous, marks, params, "reach", False, began)


def frontier(old: Graph, new: Graph, batch: Batch, previous: DataFrame, params: Params = Params()) -> RankResult:
    """A set that starts next to the batch and grows where ranks move by more than the frontier tolerance."""
    began = time.monotonic()
    marks = written(mark.initial(new, batch), "marks")
    return _restricted(new, previous, marks, params, "frontier", True, began)


def run(name: str, old: Graph, new: Graph, batch: Batch, previous: DataFrame, params: Params = Params()) -> RankResult:
    """A method by name, on the snapshot after a batch."""
    calls: dict[str, Callable[[], RankResult]] = {
        "cold": lambda: cold(new, params),
        "warm": lambda: warm(new, previous, params),
        "reach": lambda: reach(old, new, batch, previous, params),
        "frontier": lambda: frontier(old, new, batch, previous, params),
    }
    if name not in calls:
        raise ValueError(f"method is one of {METHODS}")
    return calls[name]()


def maintain(graph: Graph, ranks: DataFrame, batches: Iterable[Batch], params: Params = Params(), method: str = "frontier", refresh_every: int | None = None) -> Iterator[tuple[Graph, RankResult]]:
    """Apply batch after batch; every ``refresh_every``-th update is a full one, so that residuals don't add up."""
    for k, raw in enumerate(batches, 1):
        batch = snapshot.normalize(raw, graph.edges)
        new = snapshot.after(graph, batch)
        full = refresh_every is not None and k % refresh_every == 0
        result = run("warm" if full else method, graph, new, batch, ranks, params)
        graph, ranks = new, kept(result.ranks)
        yield graph, result
