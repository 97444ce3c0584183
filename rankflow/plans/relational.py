"""The relational surface around the methods: one query for each operator."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankflow.graphs import table
from rankflow.plans.queries import Registry


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` for its key at or before its time: a union and a window, no range join."""
    both = left.select(key, at, F.lit(1).alias("_l"), *[c for c in left.columns if c not in (key, at)], F.lit(None).cast(right.schema[value].dataType).alias(value)).unionByName(
        right.select(key, at, F.lit(0).alias("_l"), value), allowMissingColumns=True
    )
    seen = Window.partitionBy(key).orderBy(at, "_l").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(seen)).where("_l = 1").drop("_l")


def in_range(points: DataFrame, ranges: DataFrame, x: str, low: str, high: str, width: float) -> DataFrame:
    """Points in half-open ranges, joined on buckets of ``width`` that a range spans."""
    b = lambda c: F.floor(F.col(c) / width)
    spread = ranges.withColumn("_b", F.explode(F.sequence(b(low), b(high))))
    return points.withColumn("_b", b(x)).join(spread, "_b").where((F.col(x) >= F.col(low)) & (F.col(x) < F.col(high))).drop("_b")


def bands_of(points: DataFrame, x: str, width: float) -> DataFrame:
    """``(band, low, high)``: as many bands of ``width`` as the least and the greatest ``x`` ask for."""
    b = lambda c: F.floor(c / width)
    band = points.select(x).agg(F.sequence(b(F.min(x)), b(F.max(x))).alias("bands")).select(F.explode("bands").alias("band"))
    return band.select("band", (F.col("band") * width).alias("low"), ((F.col("band") + 1) * width).alias("high"))


def add(r: Registry) -> None:
    t = table
    cents = lambda e: F.round(F.sum(e) * 100).cast("long")

    r.add("filter_project", lambda s, d: t(s, d, "lineitem").where("l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_linestatus LIKE 'F%'").select("l_orderkey", "l_linenumber", "l_partkey"),
          "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_linestatus LIKE 'F%'")
    r.add("join_inner", lambda s, d: t(s, d, "customer").join(t(s, d, "nation"), F.expr("c_nationkey = n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n")),
          "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
    r.add("join_merge_hint", lambda s, d: t(s, d, "orders").hint("merge").join(t(s, d, "customer").select("c_custkey", "c_mktsegment"), F.expr("o_custkey = c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")),
          "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
    r.add("join_full", lambda s, d: t(s, d, "supplier").select("s_suppkey", "s_nationkey").join(t(s, d, "nation").select("n_nationkey", "n_name"), F.expr("s_nationkey = n_nationkey"), "full"),
          "SELECT s_suppkey, s_nationkey, n_nationkey, n_name FROM supplier FULL JOIN nation ON s_nationkey = n_nationkey")
    r.add("join_semi", lambda s, d: t(s, d, "customer").select("c_custkey").join(t(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi"),
          "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
    r.add("join_anti", lambda s, d: t(s, d, "part").select("p_partkey").join(t(s, d, "lineitem").where("l_quantity > 45").select(F.col("l_partkey").alias("p_partkey")), "p_partkey", "left_anti"),
          "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")
    bands = "SELECT i AS band, i * 50000.0 AS low, (i + 1) * 50000.0 AS high FROM (SELECT unnest(range(a, b + 1)) AS i FROM (SELECT CAST(floor(min(o_totalprice) / 50000) AS BIGINT) AS a, CAST(floor(max(o_totalprice) / 50000) AS BIGINT) AS b FROM orders))"
    r.add("join_range", lambda s, d: in_range(t(s, d, "orders").select("o_orderkey", "o_totalprice"), bands_of(t(s, d, "orders"), "o_totalprice", 50000.0), "o_totalprice", "low", "high", 50000.0).select("o_orderkey", "band"),
          f"SELECT o_orderkey, band FROM orders JOIN ({bands}) ON o_totalprice >= low AND o_totalprice < high")
    r.add("join_interval", lambda s, d: _interval(s, d), "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
    r.add("join_as_of", lambda s, d: as_of(t(s, d, "events").where("event_type = 'purchase'").select("user_id", "ts", "event_id"), t(s, d, "events").where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("view_id")), "user_id", "ts", "view_id").select("event_id", "view_id"),
          "SELECT p.event_id, v.view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS view_id FROM events WHERE event_type = 'view' GROUP BY 1, 2) v ON p.user_id = v.user_id AND p.ts >= v.ts")
    r.add("two_hop", lambda s, d: _two_hop(s, d), "WITH e AS (SELECT DISTINCT o_custkey AS a, l_suppkey AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey) SELECT x.b AS a, y.b, count(*) AS common FROM e x JOIN e y ON x.a = y.a AND x.b < y.b GROUP BY 1, 2")
    r.add("agg_basic", lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), cents("l_extendedprice").alias("price"), F.max("l_tax").alias("top_tax"), F.min("l_quantity").alias("low"), F.count_if(F.col("l_discount") > 0.05).alias("discounted")),
          "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(round(sum(l_extendedprice) * 100) AS BIGINT) AS price, max(l_tax) AS top_tax, min(l_quantity) AS low, count_if(l_discount > 0.05)::BIGINT AS discounted FROM lineitem GROUP BY 1, 2")
    r.add("agg_distinct", lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")),
          "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
    # whether sketches are within their bounds of the exact values
    near = lambda a, b, e: (F.abs(a / b - 1) <= e)
    r.add("agg_approx", lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(near(F.approx_count_distinct("l_partkey", 0.02), F.count_distinct("l_partkey"), 0.1).alias("parts"), near(F.percentile_approx("l_extendedprice", 0.5), F.percentile("l_extendedprice", 0.5), 0.02).alias("median")),
          "SELECT DISTINCT l_returnflag, TRUE AS parts, TRUE AS median FROM lineitem")
    r.add("agg_grouping_sets", lambda s, d: _views(s, d).sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n, CAST(grouping_id() AS BIGINT) AS g FROM rf_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"),
          "SELECT o_orderstatus, o_orderpriority, count(*) AS n, CAST(grouping_id(o_orderstatus, o_orderpriority) AS BIGINT) AS g FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
    r.add("agg_pivot", lambda s, d: t(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).fillna(0),
          "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY 1")
    r.add("unpivot", lambda s, d: t(s, d, "part").select("p_partkey", F.col("p_size").cast("double"), "p_retailprice").unpivot("p_partkey", ["p_size", "p_retailprice"], "name", "x"),
          "SELECT p_partkey, 'p_size' AS name, CAST(p_size AS DOUBLE) AS x FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")
    r.add("agg_collect", lambda s, d: t(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_set("n_name")), ",").alias("names")),
          "SELECT n_regionkey, string_agg(DISTINCT n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
    w = lambda: Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    r.add("window_ranks", lambda s, d: t(s, d, "customer").select("c_custkey", F.row_number().over(w()).alias("rn"), F.ntile(4).over(w()).alias("quarter"), F.lag("c_custkey").over(w()).alias("before")),
          "SELECT c_custkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(ntile(4) OVER w AS INTEGER) AS quarter, lag(c_custkey) OVER w AS before FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)")
    run = lambda: Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    r.add("window_frames", lambda s, d: t(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(run().rowsBetween(Window.unboundedPreceding, 0)), 2).alias("running"), F.count(F.lit(1)).over(run().rowsBetween(-2, 2)).alias("near")),
          "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS running, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM orders")
    r.add("topk_per_group", lambda s, d: t(s, d, "customer").withColumn("rn", F.row_number().over(w())).where("rn <= 3").select("c_nationkey", "c_custkey"),
          "SELECT c_nationkey, c_custkey FROM customer QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) <= 3")
    ids = lambda s, d, where: t(s, d, "lineitem").where(where).select("l_partkey")
    for name, op, word in (("union", "union", "UNION ALL"), ("intersect_all", "intersectAll", "INTERSECT ALL"), ("except_all", "exceptAll", "EXCEPT ALL")):
        r.add(f"set_{name}", lambda s, d, op=op: getattr(ids(s, d, "l_quantity < 20"), op)(ids(s, d, "l_tax > 0.04")), f"SELECT l_partkey FROM lineitem WHERE l_quantity < 20 {word} SELECT l_partkey FROM lineitem WHERE l_tax > 0.04")
    r.add("subquery_correlated", lambda s, d: _views(s, d).sql("SELECT o_orderkey FROM rf_orders o WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM rf_orders i WHERE i.o_custkey = o.o_custkey)"),
          "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
    r.add("strings_urls", lambda s, d: t(s, d, "pages").select("page_id", F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).cast("long").alias("links"), F.md5("url").alias("digest")),
          "SELECT page_id, split_part(url, '/', 3) AS host, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS links, md5(url) AS digest FROM pages")
    r.add("dates", lambda s, d: t(s, d, "orders").groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.max(F.dayofweek("o_orderdate")).alias("top")),
          "SELECT CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS month, count(*) AS n, CAST(max(dayofweek(o_orderdate) + 1) AS INTEGER) AS top FROM orders GROUP BY 1")
    r.add("json_props", lambda s, d: t(s, d, "events").select(F.from_json("props", "k int").alias("p")).groupBy("p.k").agg(F.count(F.lit(1)).alias("n")),
          "SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
    r.add("arrays", lambda s, d: t(s, d, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)), 9).alias("norm")),
          "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 9) AS norm FROM embeddings")
    r.add("conditional_nulls", lambda s, d: t(s, d, "supplier").select("s_suppkey", F.when(F.col("s_acctbal") < 0, "debt").when(F.col("s_acctbal") < 5000, "low").otherwise("high").alias("band"), F.nullif("s_nationkey", F.lit(0)).alias("nation")),
          "SELECT s_suppkey, CASE WHEN s_acctbal < 0 THEN 'debt' WHEN s_acctbal < 5000 THEN 'low' ELSE 'high' END AS band, nullif(s_nationkey, 0) AS nation FROM supplier")


def _views(spark: SparkSession, sf_dir: str) -> SparkSession:
    table(spark, sf_dir, "orders").createOrReplaceTempView("rf_orders")
    return spark


def _interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of a user's events within an hour, joined on the hour and the next, so that a busy user is spread out."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600).alias("hour"))
    a = events.select(F.col("event_id").alias("a_id"), "user_id", F.col("ts").alias("a_ts"), F.explode(F.array(F.col("hour"), F.col("hour") + 1)).alias("hour"))
    return a.join(events, ["user_id", "hour"]).where("ts > a_ts AND ts <= a_ts + INTERVAL 1 HOUR").select("a_id", F.col("event_id").alias("b_id"))


def _two_hop(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders, lines = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    e = orders.join(lines, F.expr("o_orderkey = l_orderkey")).select("o_custkey", "l_suppkey").distinct()
    x, y = e.select("o_custkey", F.col("l_suppkey").alias("a")), e.select("o_custkey", F.col("l_suppkey").alias("b"))
    return x.join(y, "o_custkey").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("common"))
