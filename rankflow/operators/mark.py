"""Which vertices an update has to look at."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankflow.model import Batch, Graph
from rankflow.operators import snapshot
from rankflow.storage import discard, written


def out_neighbours(edges: DataFrame, ids: DataFrame, few: list | None = None) -> DataFrame:
    """Distinct ends of the edges that leave ``ids(id)``; ``few`` are these if they are few."""
    return snapshot.touching(edges, "src", ids, few, "id").select(F.col("dst").alias("id")).distinct()


def sources(batch: Batch) -> DataFrame:
    return batch.changed().select(F.col("src").alias("id")).distinct()


def initial(new: Graph, batch: Batch) -> DataFrame:
    """Out-neighbours, before or after the batch, of every vertex that an edge of the batch leaves.

    The old edges are among the new ones and the deleted ones, so one scan does.
    """
    both = new.edges.select("src", "dst").union(batch.dels.select("src", "dst"))
    start = sources(batch)
    return out_neighbours(both, start, snapshot.listed(start))


def expand(new: Graph, movers: DataFrame) -> DataFrame:
    """Out-neighbours in the new snapshot of vertices that moved."""
    return out_neighbours(new.edges, movers)


def reachable(edges: DataFrame, start: DataFrame, include_sources: bool = False, max_depth: int | None = None) -> DataFrame:
    """All ids reachable from ``start(id)``; a start itself if an edge leads back to it.

    Without a bound on the depth, vertices that edges join both ways are first
    contracted, as who reaches one of them reaches all: long two-way chains
    then cost rounds in the logarithm of their length.  At most ``LOCAL`` edges are
    walked on arrays of the driver instead.
    """
    if max_depth is not None:
        return _traversed(edges, start, include_sources, max_depth)
    edges = written(edges.select("src", "dst"), "edges")
    if edges.count() <= LOCAL:
        out = _walked(edges, start, include_sources)
        discard(edges)
        return out
    groups = two_way_groups(edges)
    name = lambda c: F.coalesce("root", c)
    of = lambda df, c: df.join(groups.select(F.col("id").alias(c), "root"), c, "left")
    among = of(of(edges, "src").withColumn("src", name("src")).drop("root"), "dst").select("src", name("dst").alias("dst"))
    small = written(among.distinct(), "edges")
    roots = of(start.select("id"), "id").select(name("id").alias("id"))
    seen = _traversed(small, roots, include_sources, None)
    out = written(seen.join(groups.select(F.col("root").alias("id"), F.col("id").alias("member")), "id", "left").select(F.coalesce("member", "id").alias("id")), "reached")
    discard(edges, groups, small, seen)
    return out


#: Edges up to which a walk is made by the driver: two numbers each.
LOCAL = 1_000_000


def _walked(edges: DataFrame, start: DataFrame, include_sources: bool) -> DataFrame:
    """The ids reached, step by step, over neighbour lists in arrays."""
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    rows = edges.toArrow()
    ends = pa.chunked_array([*rows.column("src").chunks, *rows.column("dst").chunks], rows.schema.field("src").type).combine_chunks().dictionary_encode()
    ids, codes = ends.dictionary, ends.indices.to_numpy()
    src, dst = codes[: len(rows)], codes[len(rows) :]
    order = np.argsort(src, kind="stable")
    after, first = dst[order], np.searchsorted(src[order], np.arange(len(ids) + 1))
    begun = start.select("id").distinct().toArrow().column("id").combine_chunks()
    known = pc.index_in(begun.cast(ids.type), ids)
    front = known.drop_null().to_numpy(zero_copy_only=False).astype(int)
    seen = np.zeros(len(ids), bool)
    if include_sources:
        seen[front] = True
    while len(front):
        n = first[front + 1] - first[front]
        at = np.repeat(first[front] - np.cumsum(n) + n, n) + np.arange(n.sum())
        found = np.unique(after[at])
        front = found[~seen[found]]
        seen[front] = True
    out = ids.filter(pa.array(seen))
    if include_sources:
        out = pa.concat_arrays([out, begun.cast(ids.type).filter(known.is_null())])
    made = edges.sparkSession.createDataFrame(pa.table({"id": out}), edges.select(F.col("src").alias("id")).schema)
    return written(made, "reached")


def two_way_groups(edges: DataFrame) -> DataFrame:
    """``(id, root)`` of vertices that edges join both ways, directly or through others.

    Each round hangs a group on its least neighbour, jumps to the roots of what has
    been hung, and keeps only the edges between different roots.
    """
    one = edges.where("src <> dst")
    links = written(one.intersect(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"))), "links")
    groups = written(links.select(F.col("src").alias("id"), F.col("src").alias("root")).distinct(), "groups")
    while not links.isEmpty():
        hung = written(links.groupBy("src").agg(F.min("dst").alias("up")).select(F.col("src").alias("v"), F.least("src", "up").alias("up")), "hung")
        while True:
            above = hung.select(F.col("v").alias("up"), F.col("up").alias("top"))
            jumped = written(hung.join(above, "up").select("v", F.col("top").alias("up"), (F.col("top") != F.col("up")).alias("moved")), "hung")
            done = jumped.where("moved").isEmpty()
            discard(hung)
            hung = jumped.select("v", "up")
            hung.scratch_path = jumped.scratch_path
            if done:
                break
        top = lambda c: hung.select(F.col("v").alias(c), F.col("up").alias(f"{c}_top"))
        fewer = written(links.join(top("src"), "src").join(top("dst"), "dst").where("src_top <> dst_top").select(F.col("src_top").alias("src"), F.col("dst_top").alias("dst")).distinct(), "links")
        grown = written(groups.join(top("root"), "root", "left").select("id", F.coalesce("root_top", "root").alias("root")), "groups")
        discard(links, groups, hung)
        links, groups = fewer, grown
    discard(links)
    return groups


def _traversed(edges: DataFrame, start: DataFrame, include_sources: bool, max_depth: int | None) -> DataFrame:
    """A round for each step; visited ids and the front are tables in the shared folder."""
    front = written(start.select("id").distinct(), "front")
    seen = written(front if include_sources else front.limit(0), "seen")
    depth = 0
    while max_depth is None or depth < max_depth:
        depth += 1
        found = written(out_neighbours(edges, front).join(seen, "id", "left_anti"), "front")
        discard(front)
        front = found
        if found.isEmpty():
            break
        grown = written(seen.union(found), "seen")
        discard(seen)
        seen = grown
    discard(front)
    return seen


def reach_set(old: Graph, new: Graph, batch: Batch, snapshots: str = "union") -> DataFrame:
    """Vertices reachable from the batch's sources: over both snapshots' edges, over the new ones, or over either in turn."""
    start = sources(batch)
    if snapshots == "union":
        return reachable(new.edges.select("src", "dst").union(batch.dels.select("src", "dst")), start)
    if snapshots == "current":
        return reachable(new.edges, start)
    if snapshots == "either":
        return reachable(old.edges, start).union(reachable(new.edges, start)).distinct()
    raise ValueError("snapshots is one of union, current, either")
