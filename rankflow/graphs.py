"""Graphs built from the given tables.

Each builder returns distinct ``(src, dst)`` without loops or nulls, with ``ts``
(the first time) where edges arrive in time order.  ``SQL`` holds the same
definitions for an independent engine.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankflow.storage import held, written


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _pairs(df: DataFrame) -> DataFrame:
    return df.where("src <> dst").select("src", "dst").distinct()


def _both(df: DataFrame) -> DataFrame:
    return df.select("src", "dst").union(df.select("dst", "src")).distinct()


def part_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts that follow each other within an order."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    return _pairs(lines.select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(order).alias("dst")))


def cust_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and the suppliers of their orders, both ways."""
    timed = cust_supp_timed(spark, sf_dir)
    return timed.select("src", "dst")


def cust_supp_timed(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    named = orders.join(lines, orders.o_orderkey == lines.l_orderkey)
    pairs = named.groupBy("o_custkey", "l_suppkey").agg(F.min("o_orderdate").alias("ts"))
    one = pairs.select(F.concat(F.lit("c"), "o_custkey").alias("src"), F.concat(F.lit("s"), "l_suppkey").alias("dst"), "ts")
    return one.union(one.select("dst", "src", "ts"))


def order_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders that follow each other in time within a nation, both ways."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    order = Window.partitionBy("c_nationkey").orderBy("o_orderdate", "o_orderkey")
    placed = orders.join(customers, orders.o_custkey == customers.c_custkey)
    return _both(_pairs(placed.select(F.col("o_orderkey").alias("src"), F.lead("o_orderkey").over(order).alias("dst"))))


def gram_path(spark: SparkSession, sf_dir: str, size: int = 6) -> DataFrame:
    """Runs of letters in the benchmark texts, each to the run one letter on."""
    text = F.regexp_replace(F.lower("text"), "[^a-z]", "")
    letters = table(spark, sf_dir, "benchmark").select(text.alias("t")).where(F.length("t") > size)
    at = letters.select("t", F.explode(F.sequence(F.lit(1), F.length("t") - size)).alias("i"))
    return _pairs(at.select(F.substring("t", F.col("i"), F.lit(size)).alias("src"), F.substring("t", F.col("i") + 1, F.lit(size)).alias("dst")))


def _links(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("url", "html")
    host = F.split_part("url", F.lit("/"), F.lit(3))
    return pages.select("url", host.alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages to the pages that they link to, by host and path; most of those are dead ends."""
    links = _links(spark, sf_dir)
    return _pairs(links.select(F.col("url").alias("src"), F.concat(F.substring_index("url", "/", 3), "href").alias("dst")))


def host_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hosts and the paths that their pages link to, both ways."""
    return _both(_pairs(_links(spark, sf_dir).select(F.col("host").alias("src"), F.col("href").alias("dst"))))


def touch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users and the things that they touched, both ways, with the first time."""
    events = table(spark, sf_dir, "events").select("user_id", "event_type", "ts", F.get_json_object("props", "$.k").alias("k"))
    named = events.select(F.concat(F.lit("u"), "user_id").alias("src"), F.concat("event_type", F.lit(":"), "k").alias("dst"), "ts").dropna()
    one = named.groupBy("src", "dst").agg(F.min("ts").alias("ts"))
    return one.union(one.select("dst", "src", "ts"))


def handoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users who follow each other on the same thing, with the first time."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", F.get_json_object("props", "$.k").cast("int").alias("k"))
    order = Window.partitionBy("k").orderBy("ts", "event_id")
    steps = events.select(F.col("user_id").alias("src"), F.lead("user_id").over(order).alias("dst"), F.lead("ts").over(order).alias("ts"))
    return steps.where("src <> dst").groupBy("src", "dst").agg(F.min("ts").alias("ts"))


#: Different vectors in a block, about: two blocks are compared in a task.
VECTORS = 8192
#: Decimals of a cosine that count.
DIGITS = 9


def near_vecs(spark: SparkSession, sf_dir: str, k: int = 5) -> DataFrame:
    """Each vector to its ``k`` nearest of the same label, by cosine and then id.

    Copies are compared once: of equal vectors only the ``k + 1`` least ids can be
    near to others.  The different vectors of a label are cut into blocks, and each
    pair of blocks is a product of matrices in a task of its own.  Cosines that are
    NaN (a vector of zeros) come first and those with a null last, as in the SQL.
    """
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.col("embedding").alias("e")).dropna(subset=["vec_id", "label"])
    shaped = vectors.withColumn("shape", F.when(F.col("e").isNull() | F.exists("e", lambda x: x.isNull()), -1).otherwise(F.size("e")))
    ranked = lambda df, by, *order: df.withColumn("r", F.row_number().over(Window.partitionBy(*by).orderBy(*order)))
    whole = shaped.where("shape >= 0")
    heads = ranked(whole, ["label", "shape", "e"], "vec_id").where(F.col("r") <= k + 1)
    classes = written(heads.groupBy("label", "shape", "e").agg(F.min("vec_id").alias("rep"), F.array_sort(F.collect_list("vec_id")).alias("heads")), "classes")

    blocks = classes.groupBy("label", "shape").agg(F.ceil(F.count(F.lit(1)) / VECTORS).alias("blocks"))
    placed = classes.drop("heads").join(blocks, ["label", "shape"]).withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")))
    met = placed.withColumn("with", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("blocks") - 1)))
    pairs = met.select("label", "shape", F.least("block", "with").alias("a"), F.greatest("block", "with").alias("b"), "block", "rep", "e")
    near = pairs.groupBy("label", "shape", "a", "b").applyInArrow(_compared(k + 1), "rep bigint, other bigint, cos bigint")
    few = ranked(near, ["rep"], F.desc("cos"), "other").where(F.col("r") <= k + 1).drop("r")
    # a class that is near stands for the least ids in it
    named = few.join(classes.select(F.col("rep").alias("other"), "heads"), "other").select("rep", "cos", F.explode("heads").alias("other"))
    best = ranked(named, ["rep"], F.desc("cos"), "other").where(F.col("r") <= k + 1)
    lists = best.groupBy("rep").agg(F.array_sort(F.collect_list(F.struct("r", "other"))).alias("near"))
    owned = whole.select("vec_id", "label", "e").join(classes.select("label", "e", "rep"), ["label", "e"]).select("vec_id", "rep").join(lists, "rep")
    others = F.slice(F.filter(F.transform("near", lambda x: x["other"]), lambda x: x != F.col("vec_id")), 1, k)
    found = owned.select(F.col("vec_id").alias("src"), F.explode(others).alias("dst"))

    # vectors that have no k others to be compared with: the least ids of the rest of their label follow
    sizes = shaped.groupBy("label", "shape").agg(F.count(F.lit(1)).alias("n"))
    lacking = shaped.drop("e").join(sizes, ["label", "shape"]).withColumn("lack", F.when(F.col("shape") < 0, k).otherwise(k + 1 - F.col("n"))).where("lack > 0")
    least = ranked(shaped.drop("e"), ["label", "shape"], "vec_id").where(F.col("r") <= k + 1).select("label", F.col("shape").alias("shape2"), F.col("vec_id").alias("dst"))
    rest = lacking.join(least, "label").where("dst <> vec_id AND (shape < 0 OR shape2 <> shape)")
    filled = ranked(rest, ["vec_id"], "dst").where("r <= lack").select(F.col("vec_id").alias("src"), "dst")
    return held(found.union(filled), classes)


def _compared(m: int) -> Callable:
    """Of the vectors of two blocks (or one), the ``m`` nearest of the other block to each: by cosine in units of its last decimal, and then id."""

    def compared(key, rows):
        import numpy as np
        import pyarrow as pa

        rows = rows.sort_by("rep")
        ids, block = rows.column("rep").to_numpy(), rows.column("block").to_numpy()
        e = np.asarray(rows.column("e").combine_chunks().flatten(), np.float64).reshape(len(ids), key[1].as_py())
        with np.errstate(all="ignore"):
            unit = e / np.sqrt((e * e).sum(1, keepdims=True))
        out = []

        def nearest(x, y) -> None:
            some = min(m, len(y))
            later = np.arange(len(y) - 1, -1, -1, dtype=np.float64)
            step = max(1, (1 << 22) // max(1, len(y)))
            for at in range(0, len(x), step):
                mine = x[at : at + step]
                with np.errstate(all="ignore"):
                    c = (unit[mine] @ unit[y].T) * 10.0**DIGITS
                c = np.trunc(c + np.copysign(0.5, c))
                c[np.isnan(c)] = 2 * 10.0**DIGITS
                # cosine and place in one whole number, which a double holds exactly
                c = c * len(y) + later
                top = np.argpartition(c, len(y) - some, axis=1)[:, len(y) - some :]
                cos = np.floor_divide(np.take_along_axis(c, top, 1), len(y))
                out.append((np.repeat(ids[mine], some), ids[y][top].ravel(), cos.ravel().astype(np.int64)))

        a, b = (np.flatnonzero(block == k.as_py()) for k in key[2:])
        if len(a) and len(b):
            nearest(a, b)
            if key[2] != key[3]:
                nearest(b, a)
        made = [np.concatenate(x) if x else np.zeros(0, np.int64) for x in (zip(*out, strict=True) if out else ((), (), ()))]
        return pa.table(dict(zip(("rep", "other", "cos"), made, strict=True)))

    return compared


def nation_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nations of customers to nations of their suppliers."""
    orders, lines = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    customers, suppliers = table(spark, sf_dir, "customer"), table(spark, sf_dir, "supplier")
    sold = orders.join(lines, orders.o_orderkey == lines.l_orderkey).select("o_custkey", "l_suppkey").distinct()
    named = sold.join(customers, sold.o_custkey == customers.c_custkey).join(suppliers, sold.l_suppkey == suppliers.s_suppkey)
    return _pairs(named.select(F.col("c_nationkey").cast("bigint").alias("src"), F.col("s_nationkey").cast("bigint").alias("dst")))


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(graph_id, src, dst)``: each turn of a conversation to the next."""
    order = Window.partitionBy("conv_id").orderBy("turn")
    said = table(spark, sf_dir, "conversations").select("conv_id", "turn")
    steps = said.select(F.col("conv_id").alias("graph_id"), F.col("turn").alias("src"), F.lead("turn").over(order).alias("dst"))
    return steps.where("src <> dst").distinct()


#: The walk-through graph: fixed values.
WALK = "2-1 2-4 2-8 4-3 1-3 1-5 12-11 12-14 3-4 5-6 11-15 14-15 6-7 6-2 7-8 7-2 8-9 9-10 9-2 10-9 13-16 13-12 15-16 16-13 16-10"


def walkthrough(spark: SparkSession, sf_dir: str = "") -> DataFrame:
    ends = F.split("e", "-")
    listed = spark.range(1).select(F.explode(F.split(F.lit(WALK), " ")).alias("e"))
    return listed.select(ends[0].cast("bigint").alias("src"), ends[1].cast("bigint").alias("dst"))


#: Customers that carry a walk-through graph: as many as it has vertices.
WALKERS = 16


def walkthroughs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The walk-through graph over the customers: 16 keys in a row carry a copy, without edges to keys that no customer has."""
    keys = table(spark, sf_dir, "customer").select("c_custkey").where("c_custkey IS NOT NULL")
    place = F.pmod("c_custkey", F.lit(WALKERS)) + 1
    edges = F.broadcast(walkthrough(spark).select(F.col("src").alias("a"), F.col("dst").alias("b")))
    steps = keys.join(edges, place == F.col("a")).select(F.col("c_custkey").alias("src"), (F.col("c_custkey") - F.col("a") + F.col("b")).alias("dst"))
    return _pairs(steps.join(keys, F.col("dst") == F.col("c_custkey"), "left_semi"))


def ring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers in a ring by key: a synthetic ring of as many places, with the customers put into them."""
    from rankflow.sources.edges import synthetic

    keys = table(spark, sf_dir, "customer").select("c_custkey").where("c_custkey IS NOT NULL").distinct()
    # partitions by range, places within each, and the sizes of those before: a row for each partition
    dealt = written(keys.repartitionByRange("c_custkey").withColumn("p", F.spark_partition_id()), "keys")
    sizes = dealt.groupBy("p").agg(F.count(F.lit(1)).alias("k"))
    ahead = sizes.select("p", (F.sum("k").over(Window.orderBy("p")) - F.col("k")).alias("ahead"))
    within = F.row_number().over(Window.partitionBy("p").orderBy("c_custkey")) - 1
    placed = dealt.withColumn("i", within).join(F.broadcast(ahead), "p").select("c_custkey", (F.col("ahead") + F.col("i")).alias("place"))
    at = lambda end, name: placed.select(F.col("place").alias(end), F.col("c_custkey").alias(name))
    places = synthetic(spark, "ring", dealt.count(), partitions=spark.sparkContext.defaultParallelism)
    named = places.withColumnsRenamed({"src": "x", "dst": "y"}).join(at("x", "src"), "x").join(at("y", "dst"), "y")
    return held(named.select("src", "dst"), dealt)


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (part_flow, cust_supp, order_chain, gram_path, page_links, host_paths, touch, handoff, near_vecs, nation_trade)
} | {"walkthrough": walkthroughs}

_HREFS = "SELECT url, split_part(url, '/', 3) AS host, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages"
_K = "CAST(json_extract_string(props, '$.k') AS INTEGER)"

#: The nearest vectors, in that SQL.
NEAR_SQL = "SELECT src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) DESC, b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id <> b.vec_id) WHERE r <= 5"

#: The ring, in that SQL.
RING_SQL = "SELECT c_custkey AS src, coalesce(lead(c_custkey) OVER (ORDER BY c_custkey), min(c_custkey) OVER ()) AS dst FROM (SELECT DISTINCT c_custkey FROM customer WHERE c_custkey IS NOT NULL)"

#: The same graphs in the SQL of an independent engine.
SQL = {
    "part_flow": "SELECT DISTINCT src, dst FROM (SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem) WHERE src <> dst",
    "cust_supp": "SELECT src, dst FROM (SELECT DISTINCT 'c' || o_custkey AS a, 's' || l_suppkey AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey), LATERAL (SELECT a AS src, b AS dst UNION ALL SELECT b, a)",
    "order_chain": "SELECT DISTINCT src, dst FROM (SELECT o_orderkey AS a, lead(o_orderkey) OVER (PARTITION BY c_nationkey ORDER BY o_orderdate, o_orderkey) AS b FROM orders JOIN customer ON o_custkey = c_custkey), LATERAL (SELECT a AS src, b AS dst UNION ALL SELECT b, a) WHERE a <> b",
    "gram_path": "SELECT DISTINCT src, dst FROM (SELECT substr(t, i, 6) AS src, substr(t, i + 1, 6) AS dst FROM (SELECT t, unnest(range(1, length(t) - 5)) AS i FROM (SELECT regexp_replace(lower(text), '[^a-z]', '', 'g') AS t FROM benchmark))) WHERE src <> dst",
    "page_links": f"SELECT DISTINCT url AS src, array_to_string(list_slice(string_split(url, '/'), 1, 3), '/') || href AS dst FROM ({_HREFS}) WHERE url <> array_to_string(list_slice(string_split(url, '/'), 1, 3), '/') || href",
    "host_paths": f"SELECT DISTINCT src, dst FROM (SELECT host AS a, href AS b FROM ({_HREFS})), LATERAL (SELECT a AS src, b AS dst UNION ALL SELECT b, a) WHERE a <> b",
    "touch": "SELECT src, dst, ts FROM (SELECT 'u' || user_id AS a, event_type || ':' || json_extract_string(props, '$.k') AS b, min(ts) AS ts FROM events GROUP BY 1, 2), LATERAL (SELECT a AS src, b AS dst UNION ALL SELECT b, a)",
    "handoff": f"SELECT src, dst, min(ts) AS ts FROM (SELECT user_id AS src, lead(user_id) OVER w AS dst, lead(ts) OVER w AS ts FROM (SELECT *, {_K} AS k FROM events) WINDOW w AS (PARTITION BY k ORDER BY ts, event_id)) WHERE src <> dst GROUP BY 1, 2",
    "nation_trade": "SELECT DISTINCT CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey",
    "turns": "SELECT DISTINCT graph_id, src, dst FROM (SELECT conv_id AS graph_id, turn AS src, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations) WHERE src <> dst",
    "walkthrough": f"SELECT DISTINCT c_custkey AS src, c_custkey - a + b AS dst FROM customer JOIN (SELECT CAST(split_part(e, '-', 1) AS BIGINT) AS a, CAST(split_part(e, '-', 2) AS BIGINT) AS b FROM (SELECT unnest(string_split('{WALK}', ' ')) AS e)) ON c_custkey % {WALKERS} + 1 = a WHERE c_custkey - a + b IN (SELECT c_custkey FROM customer)",
}
