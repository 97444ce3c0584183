"""Functions that SQL users call: vectorised, aggregated, and one that ranks many small graphs in a pass."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType, StructType


def cosine(a: Column | str, b: Column | str) -> Column:
    """Cosine of two vectors, in built-in expressions; null if one has no length."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, p: s + p)
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def canonical_url(url: Column | str) -> Column:
    """Lower-case scheme and host, no fragment, no default port, no slash at the end of the path."""
    u = F.regexp_replace(url, "#.*$", "")
    scheme, host = F.lower(F.split_part(u, F.lit("//"), F.lit(1))), F.lower(F.split_part(u, F.lit("/"), F.lit(3)))
    bare = F.when(scheme == "https:", F.regexp_replace(host, ":443$", "")).otherwise(F.regexp_replace(host, ":80$", ""))
    return F.concat(scheme, F.lit("//"), bare, F.regexp_replace(F.regexp_replace(u, "^[^/]*//[^/?]*", ""), "/+([?]|$)", "$1"))


@pandas_udf(DoubleType())
def geometric_mean(x: pd.Series) -> float:
    import numpy as np

    return float(np.exp(np.log(x).mean())) if len(x) else None


@udtf(returnType=StructType().add("graph_id", LongType()).add("id", LongType()).add("rank", DoubleType()))
class SmallGraphRank:
    """Ranks of one small graph, given its edges: ``SELECT * FROM small_graph_rank(TABLE(e) PARTITION BY graph_id)``.

    A graph has to fit into a worker; large ones go through the methods.
    """

    def __init__(self) -> None:
        self.graph, self.edges = None, set()

    def eval(self, row) -> None:
        self.graph = row["graph_id"]
        self.edges.add((row["src"], row["dst"]))

    def terminate(self) -> Iterator[tuple[int, int, float]]:
        ids = sorted({x for e in self.edges for x in e})
        edges = self.edges | {(x, x) for x in ids}
        degree = dict.fromkeys(ids, 0)
        for s, _ in edges:
            degree[s] += 1
        rank = dict.fromkeys(ids, 1 / len(ids)) if ids else {}
        for _ in range(500):
            new = dict.fromkeys(ids, (1 - 0.85) / len(ids))
            for s, d in edges:
                new[d] += 0.85 * rank[s] / degree[s]
            moved = max(abs(new[x] - rank[x]) for x in ids)
            rank = new
            if moved <= 1e-15:
                break
        for x in ids:
            yield self.graph, x, rank[x]


def register(spark: SparkSession, ranks: DataFrame | None = None, batch: DataFrame | None = None) -> None:
    """Make the functions, and views ``ranks`` and ``batches``, known to SQL."""
    spark.udf.register("geometric_mean", geometric_mean)
    spark.udtf.register("small_graph_rank", SmallGraphRank)
    for name, df in (("ranks", ranks), ("batches", batch)):
        if df is not None:
            df.createOrReplaceTempView(name)


def rank_small_graphs(edges: DataFrame) -> DataFrame:
    """``(graph_id, id, rank)`` of many small graphs, ``(graph_id, src, dst)``, through the table function."""
    spark = edges.sparkSession
    register(spark)
    edges.createOrReplaceTempView("rf_small_edges")
    return spark.sql("SELECT * FROM small_graph_rank(TABLE(SELECT graph_id, src, dst FROM rf_small_edges) PARTITION BY graph_id)").select("graph_id", "id", F.col("rank"))
