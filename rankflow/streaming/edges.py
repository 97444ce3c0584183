"""Streams of edges from event files, and ranks maintained batch by batch."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery
from pyspark.sql.types import StructType

from rankflow.model import Batch, Params
from rankflow.operators import methods, snapshot
from rankflow.storage import discard, shared_folder, written

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, pattern: str = "events.parquet", files_per_trigger: int | None = None) -> DataFrame:
    """Events with ``ts`` as an instant, which watermarks need, and the touched thing ``k``."""
    reader = spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    raw = reader.parquet(path)
    return raw.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("int").alias("k"))


def edge_stream(events: DataFrame) -> DataFrame:
    """``(src, dst, ts)``: users and the things that they touch."""
    return events.select(F.concat(F.lit("u"), "user_id").alias("src"), F.concat("event_type", F.lit(":"), "k").alias("dst"), "ts")


def with_watermark(df: DataFrame, delay: str = "1 hour") -> DataFrame:
    return df.withWatermark("ts", delay)


def window_counts(df: DataFrame, kind: str = "tumbling", width: str = "1 day", slide: str = "6 hours", gap: str = "2 hours", key: str = "user_id") -> DataFrame:
    """Events in tumbling or sliding windows, or in the sessions of a key."""
    if kind == "session":
        by = [F.session_window("ts", gap).alias("w"), F.col(key)]
    elif kind in ("tumbling", "sliding"):
        by = [F.window("ts", width, slide if kind == "sliding" else None).alias("w")]
    else:
        raise ValueError("kind is one of tumbling, sliding, session")
    named = [F.col("w.start").cast("timestamp_ntz").alias("window_start"), *([F.col(key)] if kind == "session" else []), "events"]
    return df.groupBy(*by).agg(F.count(F.lit(1)).alias("events")).select(*named)


def dedup_edges(edges: DataFrame) -> DataFrame:
    """The first of equal edges within the watermark."""
    return edges.dropDuplicatesWithinWatermark(["src", "dst"])


def viewed_then_bought(events: DataFrame, within: str = "1 hour", first: str = "view", then: str = "purchase") -> DataFrame:
    """Pairs of a user's events, the second at most ``within`` after the first; watermarks on both sides bound the state."""
    side = lambda kind, name: events.where(F.col("event_type") == kind).select(F.col("user_id").alias(f"{name}_user"), F.col("event_id").alias(name), F.col("ts").alias(f"{name}_ts"))
    a = side(first, "a").withWatermark("a_ts", "1 hour")
    b = side(then, "b").withWatermark("b_ts", "1 hour")
    meet = f"a_user = b_user AND b_ts > a_ts AND b_ts <= a_ts + INTERVAL {within}"
    return a.join(b, F.expr(meet)).select(F.col("a_user").alias("user_id"), F.col("a").alias("first_id"), F.col("b").alias("then_id"))


def with_attributes(edges: DataFrame, attributes: DataFrame, key: str) -> DataFrame:
    """A stream joined with a static table."""
    return edges.join(attributes, key, "left")


class DegreeProcessor(StatefulProcessor):
    """Keeps the number of events of each user; a row with the new number for each batch."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.total = handle.getValueState("total", "n bigint")

    def handleInputRows(self, key, rows, timer_values) -> Iterator:
        import pandas as pd

        n = (self.total.get()[0] if self.total.exists() else 0) + sum(len(r) for r in rows)
        self.total.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [n]})

    def close(self) -> None:
        pass


class HandoffProcessor(StatefulProcessor):
    """Keeps the last user of each thing, and makes an edge to the next one; rows of a batch come in order of time."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "user bigint")

    def handleInputRows(self, key, rows, timer_values) -> Iterator:
        import pandas as pd

        some = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        before = int(self.last.get()[0]) if self.last.exists() else None
        out = []
        for user, ts in zip(some["user_id"], some["ts"], strict=True):
            if before is not None and before != user:
                out.append((before, int(user), ts))
            before = int(user)
        self.last.update((before,))
        yield pd.DataFrame(out, columns=["src", "dst", "ts"])

    def close(self) -> None:
        pass


def stateful(events: DataFrame, processor: StatefulProcessor, key: str, schema: str | StructType) -> DataFrame:
    """A stream through a stateful processor; its state is kept in RocksDB, which the session has to name as its state store."""
    return events.groupBy(key).transformWithStateInPandas(processor, schema, "Update", "None")


def drained(df: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """What a stream writes until its files are used up, as a table in the shared folder."""
    spark = df.sparkSession
    base = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    out = f"{base}/out"

    def keep(batch: DataFrame, k: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={k}")

    query = df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint or f"{base}/state").foreachBatch(keep).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(StructType([*df.schema.fields])).option("recursiveFileLookup", "true").parquet(out)


def maintain(edges: DataFrame, store: str, params: Params = Params()) -> StreamingQuery:
    """Keep ranks fresh under a stream of edges; with a column ``op``, rows of ``-`` are deleted, those that expire as well.

    Version ``t`` of edges and ranks lies in ``store``; a micro-batch ``k`` makes
    version ``k + 1`` from version ``k``, by the frontier method.  The same batch
    run again writes the same version, so a restart is harmless.  Vertices that
    the batch brings are added first, isolated and with scaled ranks, which is exact.
    """
    spark = edges.sparkSession

    def update(rows: DataFrame, k: int) -> None:
        old_edges, ranks = snapshot.read_version(spark, f"{store}/edges", k), snapshot.read_version(spark, f"{store}/ranks", k)
        rows = rows if "op" in rows.columns else rows.withColumn("op", F.lit("+"))
        fresh = snapshot.clean_edges(rows.where("op <> '-'")).where("src <> dst")
        gone = snapshot.clean_edges(rows.where("op = '-'"))
        known = ranks.select("id")
        added = snapshot.vertices_of(fresh).join(known, "id", "left_anti")
        n_old, n_add = known.count(), added.count()
        ranks = snapshot.rescale(ranks, n_old, n_old + n_add, added)
        vertices = known.union(added)
        old = snapshot.materialised(snapshot.prepare(old_edges, vertices))
        drawn = snapshot.normalize(Batch(fresh, gone), old.edges)
        batch = Batch(written(drawn.ins, "ins"), written(drawn.dels, "dels"))
        new = snapshot.after(old, batch)
        kept = methods.kept(ranks)
        result = methods.frontier(old, new, batch, kept, params)
        snapshot.write_version(new.edges, f"{store}/edges", k + 1)
        snapshot.write_version(result.ranks, f"{store}/ranks", k + 1)
        discard(result.ranks, result.affected, kept, batch.ins, batch.dels, old.vertices, old.edges_w, old.in_w)

    return edges.writeStream.option("checkpointLocation", f"{store}/state").foreachBatch(update).trigger(availableNow=True).start()


def start_store(spark: SparkSession, edges: DataFrame, store: str, params: Params = Params()) -> None:
    """Version 0: a graph and its ranks from scratch."""
    graph = snapshot.materialised(snapshot.prepare(edges))
    snapshot.write_version(graph.edges, f"{store}/edges", 0)
    snapshot.write_version(methods.cold(graph, params).ranks, f"{store}/ranks", 0)
