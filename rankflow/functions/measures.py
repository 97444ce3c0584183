"""Measures of cost and accuracy."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankflow.model import Graph, RankResult
from rankflow.operators import kernel


def timed(call: Callable[[], RankResult]) -> tuple[RankResult, float]:
    """A result and its seconds; inputs are materialised before, results inside."""
    began = time.monotonic()
    return call(), time.monotonic() - began


def geomean(df: DataFrame, value: str, *by: str) -> DataFrame:
    return df.groupBy(*by).agg(F.exp(F.avg(F.log(value))).alias(value))


def relative(df: DataFrame, value: str, key: str, base: str, *by: str) -> DataFrame:
    """Geometric means by ``key``, over that of the row whose key is ``base``."""
    means = geomean(df, value, key, *by)
    first = means.where(F.col(key) == base).select(*by, F.col(value).alias("_base"))
    joined = means.join(first, list(by)) if by else means.crossJoin(F.broadcast(first))  # one row
    return joined.select(*by, key, (F.col(value) / F.col("_base")).alias("relative"))


def speedup(df: DataFrame, value: str, fast: str, *by: str, key: str = "method") -> DataFrame:
    """How many times the means of others are those of ``fast``."""
    return relative(df, value, key, fast, *by).where(F.col(key) != fast).withColumnRenamed("relative", "speedup")


def _apart(a: DataFrame, b: DataFrame):
    joined = a.select("id", F.col("rank").alias("x")).join(b.select("id", F.col("rank").alias("y")), "id", "full")
    return joined.select(F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0))).alias("d"))


def l1(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row, ``l1``: the sum of absolute differences; a missing vertex counts as 0."""
    return _apart(a, b).agg(F.coalesce(F.sum("d"), F.lit(0.0)).alias("l1"))


def linf(a: DataFrame, b: DataFrame) -> DataFrame:
    return _apart(a, b).agg(F.coalesce(F.max("d"), F.lit(0.0)).alias("linf"))


def mass(ranks: DataFrame) -> DataFrame:
    """One row, ``drift``: how far the ranks are from adding up to 1."""
    return ranks.agg(F.abs(F.coalesce(F.sum("rank"), F.lit(0.0)) - 1.0).alias("drift"))


def residual(graph: Graph, ranks: DataFrame, alpha: float = 0.85) -> DataFrame:
    """One row: what one more step over all vertices would change, and the bound that this sets on the error."""
    return l1(ranks, kernel.pull_step(graph, ranks, alpha)).select(F.col("l1").alias("residual"), (F.col("l1") / (1.0 - alpha)).alias("certificate"))


def affected_fraction(result: RankResult, n: int) -> float:
    """Share of the vertices that were marked in the end."""
    return result.affected.count() / max(1, n)


def work(result: RankResult) -> dict:
    """Vertices recomputed and in-edges of marked ones read over all rounds, rounds, and seconds."""
    return {"vertex_updates": result.vertex_updates, "edges_read": result.edges_read, "iterations": result.iterations, "seconds": result.seconds_total}


def rank_correlation(a: DataFrame, b: DataFrame, digits: int = 12) -> DataFrame:
    """One row, ``correlation``: how far two rankings order the same vertices alike, by their places; equal ranks by id."""

    def placed(df: DataFrame, name: str) -> DataFrame:
        rows = df.select("id", F.round("rank", digits).alias("rank")).repartitionByRange(F.desc("rank"), "id").withColumn("p", F.spark_partition_id())
        sizes = rows.groupBy("p").agg(F.count(F.lit(1)).alias("k"))
        ahead = sizes.select("p", (F.sum("k").over(Window.orderBy("p")) - F.col("k")).alias("ahead"))  # a row for each partition
        within = F.row_number().over(Window.partitionBy("p").orderBy(F.desc("rank"), "id"))
        return rows.withColumn("i", within).join(F.broadcast(ahead), "p").select("id", (F.col("ahead") + F.col("i")).alias(name))

    both = placed(a, "x").join(placed(b, "y"), "id")
    return both.agg(F.corr(F.col("x").cast("double"), F.col("y").cast("double")).alias("correlation"))


def top_k(ranks: DataFrame, k: int) -> DataFrame:
    """The ``k`` highest ranks, equal ones by id."""
    return ranks.orderBy(F.desc("rank"), "id").limit(k)


def topk_overlap(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """One row, ``overlap``: how much of the top ``k`` two rankings share."""
    both = top_k(a, k).select("id").join(top_k(b, k).select("id"), "id")
    return both.agg((F.count(F.lit(1)) / k).alias("overlap"))


def graph_stats(graph: Graph) -> DataFrame:
    """One row: vertices, edges with loops, average degree."""
    return graph.edges.agg(F.count(F.lit(1)).alias("edges")).select(
        F.lit(graph.n).cast("long").alias("vertices"), "edges", (F.col("edges") / graph.n).alias("avg_degree")
    )


def gini(ranks: DataFrame, buckets: int = 1024) -> DataFrame:
    """One row, ``gini``: the skew of the ranks, exact, by sums within ranges of equal size.

    Ranks are ranged over partitions and numbered within; ``buckets`` rows of sums
    give each range its offset, so that no task sees all ranks.
    """
    lows = ranks.agg(F.percentile_approx("rank", [k / buckets for k in range(1, buckets)], 100 * buckets).alias("cuts"))
    placed = ranks.crossJoin(F.broadcast(lows)).select("rank", F.size(F.filter("cuts", lambda c: c < F.col("rank"))).alias("b"))  # one row
    sizes = placed.groupBy("b").agg(F.count(F.lit(1)).alias("k"))
    ahead = sizes.select("b", (F.sum("k").over(Window.orderBy("b")) - F.col("k")).alias("ahead"))  # at most ``buckets`` rows
    i = F.row_number().over(Window.partitionBy("b").orderBy("rank")) + F.col("ahead")
    rows = placed.join(F.broadcast(ahead), "b").select("rank", i.alias("i"))
    sums = rows.agg(F.sum(F.col("i") * F.col("rank")).alias("ir"), F.sum("rank").alias("r"), F.count(F.lit(1)).alias("n"))
    return sums.select((2 * F.col("ir") / (F.col("n") * F.col("r")) - (F.col("n") + 1) / F.col("n")).alias("gini"))
