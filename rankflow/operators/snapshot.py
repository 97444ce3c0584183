"""Snapshots of a graph: preparing, changing, comparing and keeping versions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankflow.model import Batch, Graph, require_columns
from rankflow.storage import bucketed, discard, written


def clean_edges(edges: DataFrame) -> DataFrame:
    """Distinct ``(src, dst)`` without nulls."""
    require_columns(edges, ("src", "dst"))
    return edges.select("src", "dst").where("src IS NOT NULL AND dst IS NOT NULL").distinct()


def vertices_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()


def self_loops(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """The edges and a loop on every vertex."""
    return edges.select("src", "dst").union(vertices.select(F.col("id").alias("src"), F.col("id").alias("dst"))).distinct()


def symmetrize(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def out_degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.count(F.lit(1)).alias("degree"))


def dead_ends(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Vertices without an out-edge."""
    return vertices.join(edges.select(F.col("src").alias("id")).distinct(), "id", "left_anti")


def weighted(edges: DataFrame) -> DataFrame:
    """``(src, dst, w)`` with ``w`` one over the out-degree of ``src``."""
    return edges.join(out_degrees(edges), "src").select("src", "dst", (1.0 / F.col("degree")).alias("w"))


def prepare(edges: DataFrame, vertices: DataFrame | None = None, dead: str = "selfloop") -> Graph:
    """A :class:`Graph` from raw edges, with the treatment of dead ends applied.

    The number of vertices is taken once, as it enters every step as a constant.
    """
    edges = clean_edges(edges)
    vertices = vertices_of(edges) if vertices is None else vertices.select("id").distinct()
    if dead == "selfloop":
        edges = self_loops(edges, vertices)
    return Graph(vertices, edges, weighted(edges), vertices.count(), dead)


#: Edges for which a layout has a bucket more; there are no more buckets than shuffle partitions.
BUCKET = 20_000


def buckets_of(spark: SparkSession, rows: int) -> int:
    return max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), rows // BUCKET))


def materialised(graph: Graph) -> Graph:
    """The graph with its tables written: vertices by id, edges by ``src`` for full steps and marks, and by ``dst`` for pulls of few vertices.

    Full steps join ranks and edges bucket by bucket, so that edges stay where they are.
    """
    plain = written(graph.edges_w if graph.patches else weighted(graph.edges), "edges")
    m = plain.count()
    k = buckets_of(graph.vertices.sparkSession, m)
    edges_w, in_w = bucketed(plain, "out", "src", k), bucketed(plain, "in", "dst", k)
    discard(plain)
    return Graph(bucketed(graph.vertices, "vertices", "id", k), edges_w.select("src", "dst"), edges_w, graph.n, graph.dead_ends, in_w, m=m)


def normalize(batch: Batch, edges: DataFrame, vertices: DataFrame | None = None) -> Batch:
    """The batch as set differences: inserts are new, deletes exist, none is in both, no loop is deleted.

    An edge asked for both ways is left as it is.  With ``vertices``, edges that
    name another vertex are rejected.
    """
    keys = ["src", "dst"]
    ins, dels = clean_edges(batch.ins), clean_edges(batch.dels)
    new = ins.join(edges, keys, "left_anti").join(dels, keys, "left_anti")
    old = dels.where("src <> dst").join(edges, keys, "left_semi").join(ins, keys, "left_anti")
    if vertices is not None:
        ends = new.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
        unknown = ends.join(vertices, "id", "left_anti")
        if not unknown.isEmpty():
            raise ValueError("an inserted edge names a vertex that the graph lacks")
    return Batch(new, old)


def apply_batch(edges: DataFrame, batch: Batch, vertices: DataFrame | None = None) -> DataFrame:
    """The edges after the batch; with ``vertices``, with their loops again."""
    out = edges.join(batch.dels, ["src", "dst"], "left_anti").union(batch.ins.select("src", "dst")).distinct()
    return out if vertices is None else self_loops(out, vertices)


#: Batches that may lie over the written layouts; one more, and they are written anew.
PATCHES = 8


def after(graph: Graph, batch: Batch) -> Graph:
    """The next snapshot, on the same vertices: the layouts as they are, but for the sources that the batch names.

    Only the out-edges of these are read and weighed anew; they are the one thing written.
    """
    if graph.patches >= PATCHES:
        graph = materialised(graph)
    changed = written(batch.changed().select("src").distinct(), "changed")
    few = listed(changed, "src")
    kept = touching(graph.edges, "src", changed, few).join(batch.dels, ["src", "dst"], "left_anti")
    patch = written(weighted(kept.union(batch.ins.select("src", "dst")).distinct()), "patch")
    rest = lambda df: df.join(changed, "src", "left_anti").select("src", "dst", "w").union(patch)
    edges_w, in_w = rest(graph.edges_w), rest(graph.by_dst)
    m = None if graph.m is None else graph.m + batch.ins.count() - batch.dels.count()
    return Graph(graph.vertices, edges_w.select("src", "dst"), edges_w, graph.n, graph.dead_ends, in_w, graph.patches + 1, m)


#: Keys up to which a filter names them, so that a layout's other buckets are not read.
LISTED = 200


def listed(ids: DataFrame, key: str = "id") -> list | None:
    """The keys, if there are but few."""
    rows = ids.select(key).limit(LISTED + 1).collect()
    return [r[0] for r in rows] if len(rows) <= LISTED else None


def touching(edges: DataFrame, key: str, ids: DataFrame, few: list | None, id_col: str | None = None) -> DataFrame:
    """The edges whose ``key`` is among ``ids``; ``few`` are these if they are few."""
    if few is not None:
        return edges.where(F.col(key).isin(few))
    return edges.join(ids.select(F.col(id_col or key).alias(key)), key, "left_semi")


def diff(old: DataFrame, new: DataFrame) -> Batch:
    """The batch that leads from one edge set to another."""
    keys = ["src", "dst"]
    return Batch(new.select(keys).join(old, keys, "left_anti"), old.select(keys).join(new, keys, "left_anti"))


def update_degrees(degrees: DataFrame, batch: Batch) -> DataFrame:
    """Out-degrees after a batch, from the degrees before it and the batch alone."""
    change = batch.signed().groupBy("src").agg(F.sum(F.expr("CASE op WHEN '+' THEN 1 ELSE -1 END")).alias("change"))
    out = degrees.join(change, "src", "full").select("src", (F.coalesce("degree", F.lit(0)) + F.coalesce("change", F.lit(0))).cast("long").alias("degree"))
    return out.where("degree > 0")


def rescale(ranks: DataFrame, n_old: int, n_new: int, added: DataFrame | None = None) -> DataFrame:
    """Ranks on a graph that grew or shrank by isolated vertices with loops: exact, as each has ``1 / n``."""
    out = ranks.select("id", (F.col("rank") * (n_old / n_new)).alias("rank"))
    return out if added is None else out.union(added.select("id", F.lit(1.0 / n_new)))


def write_version(table: DataFrame, path: str, t: int) -> None:
    """Version ``t`` of a table, as one partition; writing it again replaces it."""
    table.write.mode("overwrite").parquet(f"{path}/t={t}")


def read_version(spark: SparkSession, path: str, t: int) -> DataFrame:
    return spark.read.parquet(f"{path}/t={t}")
