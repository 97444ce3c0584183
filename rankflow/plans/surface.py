"""More of the relational surface: forms of joins, windows, subqueries, generators and functions, a query for each."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankflow.graphs import table as t
from rankflow.plans.queries import Registry


def viewed(spark: SparkSession, sf_dir: str, *names: str) -> SparkSession:
    """The session with tables as views ``rf_<name>``."""
    for name in names:
        t(spark, sf_dir, name).createOrReplaceTempView(f"rf_{name}")
    return spark


def sampled(df: DataFrame, key: str, share: float, seed: int = 1) -> DataFrame:
    """Rows whose key falls into a share of all keys by a hash that other engines have: the same rows on every run."""
    from rankflow.operators.batches import DIGITS, drawn

    return df.where(drawn(F.lit(seed), F.col(key)) < share * 2.0 ** (4 * DIGITS))


def add(r: Registry) -> None:
    def both(name: str, sql: str, *tables: str, duck: str | None = None) -> None:
        """A query that both engines run from the same text, but for the names of tables."""

        def query(spark: SparkSession, sf_dir: str) -> DataFrame:
            text = sql
            for x in tables:
                text = text.replace(f"@{x}", f"rf_{x}")
            return viewed(spark, sf_dir, *tables).sql(text)

        r.add(name, query, (duck or sql).replace("@", ""))

    r.add("join_shuffled_hash", lambda s, d: t(s, d, "orders").select("o_custkey").hint("shuffle_hash").join(t(s, d, "customer").select("c_custkey", "c_nationkey"), F.expr("o_custkey = c_custkey")).groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n")),
          "SELECT c_nationkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
    both("join_left_right", "SELECT c_custkey, o_orderkey FROM @customer LEFT JOIN @orders ON o_custkey = c_custkey UNION ALL SELECT c_custkey, o_orderkey FROM @orders RIGHT JOIN @customer ON o_custkey = c_custkey", "customer", "orders")
    both("join_cross", "SELECT n_nationkey, r_regionkey FROM @nation CROSS JOIN @region", "nation", "region")  # two tables of fixed size
    both("filter_patterns", "SELECT p_partkey FROM @part WHERE p_type RLIKE '^[A-M].*[A-Z]$' AND NOT (p_size <=> 7) AND p_brand IS NOT NULL", "part", duck="SELECT p_partkey FROM @part WHERE regexp_matches(p_type, '^[A-M].*[A-Z]$') AND p_size IS DISTINCT FROM 7 AND p_brand IS NOT NULL")
    both("agg_statistics", "SELECT l_returnflag, round(avg(l_quantity), 9) AS mean, round(stddev_samp(l_quantity), 6) AS spread, round(var_pop(l_tax), 9) AS wide, max_by(l_orderkey, l_extendedprice * 1e7 + l_orderkey) AS dearest, bool_or(l_tax > 0.07) AS taxed FROM @lineitem GROUP BY l_returnflag", "lineitem")
    ranks = "rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd"
    both("window_rank_kinds", f"SELECT c_custkey, {ranks} FROM @customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)", "customer",
         duck=f"SELECT c_custkey, {ranks.replace('rank() OVER w AS r,', 'CAST(rank() OVER w AS INTEGER) AS r,').replace('dense_rank() OVER w AS dr', 'CAST(dense_rank() OVER w AS INTEGER) AS dr')} FROM @customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
    frame = "(PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
    both("window_values", f"SELECT o_orderkey, lead(o_orderkey, 2) OVER v AS later, first_value(o_orderkey) OVER w AS first, last_value(o_orderkey) OVER w AS last, nth_value(o_orderkey, 2) OVER w AS second FROM @orders WINDOW w AS {frame}, v AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)", "orders")
    both("window_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 3 PRECEDING AND 3 FOLLOWING) AS near, count(*) OVER (PARTITION BY p_brand) AS every FROM @part", "part")

    def placed(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Places of a global sort of several keys: partitions by range, rows by their order within, sizes before them added."""
        keys = [F.col("s_nationkey").desc_nulls_last(), F.col("s_acctbal").asc_nulls_first(), F.col("s_suppkey")]
        rows = t(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal").repartitionByRange(*keys).withColumn("p", F.spark_partition_id())
        sizes = rows.groupBy("p").agg(F.count(F.lit(1)).alias("k"))
        ahead = sizes.select("p", (F.sum("k").over(Window.orderBy("p")) - F.col("k")).alias("ahead"))  # a row for each partition
        within = F.row_number().over(Window.partitionBy("p").orderBy(*keys))
        return rows.withColumn("i", within).join(F.broadcast(ahead), "p").select("s_suppkey", (F.col("ahead") + F.col("i")).alias("place"))

    r.add("sort_global", placed, "SELECT s_suppkey, row_number() OVER (ORDER BY s_nationkey DESC NULLS LAST, s_acctbal ASC NULLS FIRST, s_suppkey) AS place FROM supplier")
    both("topk_offset", "SELECT o_orderkey FROM @orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10", "orders")
    for name, word in (("union_distinct", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):
        both(f"set_{name}", f"SELECT l_partkey FROM @lineitem WHERE l_quantity > 49 {word} SELECT l_partkey FROM @lineitem WHERE l_tax > 0.07", "lineitem")
    both("subquery_in_exists", "SELECT c_custkey FROM @customer c WHERE c_nationkey IN (SELECT n_nationkey FROM @nation WHERE n_regionkey = 1) AND EXISTS (SELECT 1 FROM @orders o WHERE o.o_custkey = c.c_custkey AND o_totalprice > 100000)", "customer", "nation", "orders")
    both("subquery_lateral_cte", "WITH s AS (SELECT o_custkey, count(*) AS k, sum(o_totalprice) AS total FROM @orders GROUP BY o_custkey) SELECT c_custkey, k, share FROM @customer JOIN s ON o_custkey = c_custkey, LATERAL (SELECT round(total / k, 2) AS share)", "orders", "customer")
    # steps of a walk down the halves of a part's number: a chain without cycles, of bounded depth
    # LIMIT ALL lifts the session's limit of a million rows for a recursion, which 20 rows a part pass at 50,000 parts
    both("recursion_depth", "WITH RECURSIVE w(start, v, depth) AS (SELECT p_partkey, p_partkey, 0 FROM @part UNION ALL SELECT start, CAST(floor(v / 2) AS BIGINT), depth + 1 FROM w WHERE v > 1 AND depth < 40) SELECT start, max(depth) AS depth, sum(v) AS total FROM (SELECT * FROM w LIMIT ALL) GROUP BY start", "part",
         duck="WITH RECURSIVE w(start, v, depth) AS (SELECT p_partkey, p_partkey, 0 FROM @part UNION ALL SELECT start, v // 2, depth + 1 FROM w WHERE v > 1 AND depth < 40) SELECT start, max(depth) AS depth, CAST(sum(v) AS BIGINT) AS total FROM w GROUP BY start")
    both("dates_arithmetic", "SELECT o_orderkey, CAST(date_add(CAST(o_orderdate AS DATE), 30) AS STRING) AS due, datediff(DATE '2030-01-01', CAST(o_orderdate AS DATE)) AS days, CAST(add_months(CAST(o_orderdate AS DATE), 2) AS STRING) AS later, extract(QUARTER FROM o_orderdate) AS quarter FROM @orders", "orders",
         duck="SELECT o_orderkey, CAST(CAST(CAST(o_orderdate AS DATE) + 30 AS DATE) AS VARCHAR) AS due, CAST(date_diff('day', CAST(o_orderdate AS DATE), DATE '2030-01-01') AS INTEGER) AS days, CAST(CAST(CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH AS DATE) AS VARCHAR) AS later, CAST(quarter(o_orderdate) AS INTEGER) AS quarter FROM @orders")
    both("math", "SELECT p_partkey, abs(p_size - 25) AS off, greatest(p_size, 10) AS most, round(ln(p_retailprice), 9) AS logarithm, round(exp(-p_size / 10.0D), 9) AS decay, round(power(p_size, 1.5D), 6) AS grown, pmod(p_partkey, 7) AS residue, p_partkey & 5 AS bits, shiftleft(p_partkey, 2) AS moved FROM @part", "part",
         duck="SELECT p_partkey, abs(p_size - 25) AS off, greatest(p_size, 10) AS most, round(ln(p_retailprice), 9) AS logarithm, round(exp(-p_size / CAST(10 AS DOUBLE)), 9) AS decay, round(power(p_size, CAST(1.5 AS DOUBLE)), 6) AS grown, p_partkey % 7 AS residue, p_partkey & 5 AS bits, p_partkey << 2 AS moved FROM @part")

    def maps(spark: SparkSession, sf_dir: str) -> DataFrame:
        entries = F.map_from_entries(F.array_sort(F.collect_list(F.struct("o_orderstatus", "n"))))
        counts = t(spark, sf_dir, "orders").groupBy("o_orderpriority", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))
        made = counts.groupBy("o_orderpriority").agg(entries.alias("m"))
        doubled = F.map_zip_with("m", "m", lambda k, a, b: a + b)
        return made.select("o_orderpriority", F.array_join(F.map_keys("m"), ",").alias("keys"), F.coalesce(F.try_element_at("m", F.lit("F")), F.lit(0)).alias("f"), F.aggregate(F.map_values(doubled), F.lit(0).cast("long"), lambda s, x: s + x).alias("twice"))

    r.add("maps", maps, "SELECT o_orderpriority, string_agg(DISTINCT o_orderstatus, ',' ORDER BY o_orderstatus) AS keys, count(*) FILTER (o_orderstatus = 'F') AS f, 2 * count(*) AS twice FROM orders GROUP BY 1")
    r.add("json_out", lambda s, d: t(s, d, "nation").select("n_nationkey", F.to_json(F.struct("n_nationkey", "n_name")).alias("j"), F.schema_of_json(F.lit('{"k": 1}')).alias("shape")),
          "SELECT n_nationkey, '{\"n_nationkey\":' || n_nationkey || ',\"n_name\":\"' || n_name || '\"}' AS j, 'STRUCT<k: BIGINT>' AS shape FROM nation")
    r.add("generators", lambda s, d: viewed(s, d, "region").sql("SELECT r_regionkey, k, v FROM rf_region LATERAL VIEW stack(2, 'name', r_name, 'size', CAST(length(r_name) AS STRING)) AS k, v UNION ALL SELECT r_regionkey, a, b FROM rf_region LATERAL VIEW inline(array(struct('x' AS a, r_name AS b))) AS a, b UNION ALL SELECT r_regionkey, 'none', e FROM rf_region LATERAL VIEW OUTER explode(CAST(array() AS ARRAY<STRING>)) AS e"),
          "SELECT r_regionkey, 'name' AS k, r_name AS v FROM region UNION ALL SELECT r_regionkey, 'size', CAST(length(r_name) AS VARCHAR) FROM region UNION ALL SELECT r_regionkey, 'x', r_name FROM region UNION ALL SELECT r_regionkey, 'none', NULL FROM region")
    r.add("sample_by_hash", lambda s, d: sampled(t(s, d, "customer").select("c_custkey", "c_mktsegment"), "c_custkey", 0.25), "SELECT c_custkey, c_mktsegment FROM customer WHERE CAST('0x' || substr(md5(concat_ws('|', 1, c_custkey)), 1, 15) AS BIGINT) < 0.25 * 1152921504606846976")
