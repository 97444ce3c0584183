"""One step of the rank equation, as a join and an aggregate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankflow.model import Graph


def incoming(edges_w: DataFrame, ranks: DataFrame) -> DataFrame:
    """``(id, s)``: the weighted ranks of each vertex's in-neighbours, summed.

    Partial sums are formed before rows move to ``dst``, which takes the load of hubs.
    """
    joined = edges_w.join(ranks.select(F.col("id").alias("src"), "rank"), "src")
    return joined.groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") * F.col("w")).alias("s"))


def pull_step(graph: Graph, ranks: DataFrame, alpha: float, targets: DataFrame | None = None) -> DataFrame:
    """``(id, rank)`` after one step, for all vertices or for ``targets(id)`` only: of these, only in-edges are joined."""
    edges_w = graph.edges_w
    if targets is not None:
        edges_w = graph.by_dst.join(targets.select(F.col("id").alias("dst")), "dst", "left_semi")
    base = graph.vertices if targets is None else targets.select("id")
    out = base.join(incoming(edges_w, ranks), "id", "left")
    rank = (1.0 - alpha) / graph.n + alpha * F.coalesce("s", F.lit(0.0))
    if graph.dead_ends == "teleport":
        if targets is not None:
            raise ValueError("a shared term for dead ends couples all vertices; a restricted step would be wrong")
        dead = ranks.join(graph.edges.select(F.col("src").alias("id")), "id", "left_anti")
        out = out.crossJoin(F.broadcast(dead.agg(F.coalesce(F.sum("rank"), F.lit(0.0)).alias("lost"))))  # one row
        rank = rank + alpha * F.col("lost") / graph.n
    return out.select("id", rank.alias("rank"))


def push_delta(graph: Graph, changes: DataFrame, alpha: float) -> DataFrame:
    """``(id, change)``: what changes of ranks, ``(id, change)``, add to their out-neighbours in one step.

    By linearity this equals a pull wherever out-degrees did not change.
    """
    moved = incoming(graph.edges_w, changes.select("id", F.col("change").alias("rank")))
    return moved.select("id", (alpha * F.col("s")).alias("change"))
