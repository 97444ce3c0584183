"""Batches of edge changes: random ones by a hash that other engines have too, and those of edges that carry a time."""

from __future__ import annotations

from collections.abc import Iterator
from datetime import datetime, timedelta

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankflow.model import Batch, Graph
from rankflow.operators import snapshot
from rankflow.storage import discard, written

#: Hexadecimal digits of a draw, 60 bits; the SQL of the queries takes as many.
DIGITS = 15
#: Deletes up to which their number is exact; beyond, each edge has its chance, and the number is within a few thousandths.
EXACT = 1_000_000


def drawn(*parts: Column) -> Column:
    """An even whole number of 60 bits for the parts."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[p.cast("string") for p in parts])), 1, DIGITS), 16, 10).cast("bigint")


def dense_positions(vertices: DataFrame, partitions: int | None = None) -> DataFrame:
    """``(id, pos)``: ids numbered from 0 in their order, without a task that sees them all.

    Ids are ranged over partitions, the partitions' sizes summed up (a row each),
    and rows numbered within.
    """
    spark = vertices.sparkSession
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = written(vertices.select("id").repartitionByRange(n, "id").withColumn("p", F.spark_partition_id()), "ranged")
    sizes = ranged.groupBy("p").agg(F.count(F.lit(1)).alias("k"))
    ahead = sizes.select("p", (F.sum("k").over(Window.orderBy("p")) - F.col("k")).alias("ahead"))  # a row for each partition
    within = F.row_number().over(Window.partitionBy("p").orderBy("id")) - 1
    return ranged.withColumn("i", within).join(F.broadcast(ahead), "p").select("id", (F.col("ahead") + F.col("i")).cast("long").alias("pos"))


def random_inserts(positions: DataFrame, n: int, count: int, seed: int) -> DataFrame:
    """``count`` pairs of vertices, each pair as likely as any; some may exist, repeat, or be loops, which go."""
    end = lambda side: F.pmod(drawn(F.lit(seed), F.col("i"), F.lit(side)), F.lit(n))
    pairs = positions.sparkSession.range(count).withColumnRenamed("id", "i").select(end("src").alias("p"), end("dst").alias("q"))
    src = positions.select(F.col("pos").alias("p"), F.col("id").alias("src"))
    dst = positions.select(F.col("pos").alias("q"), F.col("id").alias("dst"))
    return pairs.join(src, "p").join(dst, "q").where("src <> dst").select("src", "dst").distinct()


def random_deletes(edges: DataFrame, m: int, count: int, seed: int) -> DataFrame:
    """``count`` of the ``m`` edges that aren't loops, each as likely as any: those of the least hashes."""
    placed = edges.where("src <> dst").select("src", "dst", drawn(F.lit(seed), F.col("src"), F.col("dst")).alias("h"))
    bound = lambda k: min(1.0, k / max(1, m)) * 2.0 ** (4 * DIGITS)
    if count > EXACT:
        return placed.where(F.col("h") < bound(count)).select("src", "dst")
    some = placed.where(F.col("h") < bound(count + 10 * count**0.5 + 50))  # more than ``count``, but for a chance of none
    return some.orderBy("h", "src", "dst").limit(count).select("src", "dst")


def generate(kind: str, graph: Graph, size: int, seed: int = 1, m: int | None = None, positions: DataFrame | None = None) -> Batch:
    """A normalised batch of about ``size`` edges: ``ins``, ``del``, or ``mix`` with four inserts to a delete.

    Inserts that exist already, repeat or are loops are fewer for it; ``signed().count()`` tells the size in effect.
    """
    share = {"ins": 1.0, "del": 0.0, "mix": 0.8}
    if kind not in share:
        raise ValueError("kind is one of ins, del, mix")
    none = graph.edges.select("src", "dst").limit(0)
    k = round(size * share[kind])
    ins = dels = none
    if k:
        ins = random_inserts(dense_positions(graph.vertices) if positions is None else positions, graph.n, k, seed)
    if size > k:
        m = graph.edges.where("src <> dst").count() if m is None else m
        dels = random_deletes(graph.edges, m, size - k, seed)
    return snapshot.normalize(Batch(ins, dels), graph.edges)


def sweep(graph: Graph, kind: str, fractions: tuple[float, ...], repeats: int = 3) -> Iterator[tuple[float, int, Batch]]:
    """``(fraction, seed, batch)`` over sizes as fractions of the edges; a size below one edge is one edge."""
    m, plain = graph.edges.count(), graph.edges.where("src <> dst").count()
    positions = written(dense_positions(graph.vertices), "positions")
    for fraction in fractions:
        for seed in range(1, repeats + 1):
            yield fraction, seed, generate(kind, graph, max(1, round(fraction * m)), seed, m=plain, positions=positions)
    discard(positions)


def base_before(edges_ts: DataFrame, start: str | datetime) -> DataFrame:
    return edges_ts.where(F.col("ts") < F.lit(str(start)).cast("timestamp_ntz")).select("src", "dst")


def by_time(edges_ts: DataFrame, start: datetime, width: timedelta, count: int) -> Iterator[Batch]:
    """Inserts of ``count`` windows in a row, from ``start`` on."""
    none = edges_ts.select("src", "dst").limit(0)
    for k in range(count):
        yield Batch(_between(edges_ts, start + k * width, start + (k + 1) * width), none)


def sliding(edges_ts: DataFrame, start: datetime, width: timedelta, keep: timedelta, count: int) -> Iterator[Batch]:
    """As :func:`by_time`, with edges deleted when they are older than ``keep``."""
    for k in range(count):
        old = _between(edges_ts, start + k * width - keep, start + (k + 1) * width - keep)
        yield Batch(_between(edges_ts, start + k * width, start + (k + 1) * width), old)


def slide(edges_ts: DataFrame, times: DataFrame, width: timedelta, keep: timedelta) -> DataFrame:
    """``(batch, src, dst, op)``: the batches of :func:`sliding` for every window, in one pass.

    Windows are numbered from the start of the first day of ``times(ts)`` to the
    one that holds its last time.  An edge enters in the window of its time and leaves in
    that of its time plus ``keep``, if the series gets there.
    """
    step, later = (x // timedelta(microseconds=1) for x in (width, keep))
    span = times.agg(F.min("ts").cast("date").cast("timestamp_ntz").alias("_first"), F.max("ts").alias("_end"))
    after = lambda c: _micros(F.col(c) - F.col("_first"))
    window = lambda micros: F.floor(micros / step).cast("int")
    placed = edges_ts.crossJoin(F.broadcast(span)).select("src", "dst", after("ts").alias("at"), window(after("_end")).alias("last"))
    moves = F.array(F.struct(window(F.col("at")).alias("batch"), F.lit("+").alias("op")), F.struct(window(F.col("at") + later).alias("batch"), F.lit("-").alias("op")))
    return placed.select("src", "dst", "last", F.explode(moves).alias("m")).where("m.batch BETWEEN 0 AND last").select("m.batch", "src", "dst", "m.op")


def _micros(interval: Column) -> Column:
    """Microseconds of an interval that isn't negative; whatever the session's time zone."""
    hours = F.extract(F.lit("DAY"), interval).cast("long") * 24 + F.extract(F.lit("HOUR"), interval)
    minutes = hours * 60 + F.extract(F.lit("MINUTE"), interval)
    return minutes * 60_000_000 + (F.extract(F.lit("SECOND"), interval) * 1_000_000).cast("long")


def _between(edges_ts: DataFrame, low: datetime, high: datetime) -> DataFrame:
    at = lambda t: F.lit(str(t)).cast("timestamp_ntz")
    return edges_ts.where((F.col("ts") >= at(low)) & (F.col("ts") < at(high))).select("src", "dst")


def windows(edges_ts: DataFrame, width: str = "1 day") -> DataFrame:
    """``(window_start, edges)``: how many edges first appear in each window."""
    return edges_ts.groupBy(F.window(F.col("ts").cast("timestamp"), width).alias("w")).agg(F.count(F.lit(1)).alias("edges")).select(F.col("w.start").cast("timestamp_ntz").alias("window_start"), "edges")
