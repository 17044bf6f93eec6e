"""Ordinary operators around search results: each a thin plan on the DataFrame or SQL API, with the same rows in SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .registry import query, read, warehouse

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def both(name: str, text: str, duck: str | None = None):
    """A query whose Spark SQL runs on the tables it names; DuckDB's text where the dialects part."""

    @query(f"rel_{name}", duck or text)
    def run(spark, sf):
        for t in TABLES:
            if t in text:
                df = read(spark, sf, t)
                for c, k in df.dtypes:  # one kind of time on both sides
                    if k == "timestamp":
                        df = df.withColumn(c, F.col(c).cast("timestamp_ntz"))
                df.createOrReplaceTempView(t)
        return spark.sql(text)


both("projection", "SELECT l_orderkey, l_linenumber, l_extendedprice * (1 - l_discount) AS net FROM lineitem WHERE l_quantity < 5")
both("predicates", "SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 20 AND p_type LIKE '%STEEL%' OR p_brand IN ('Brand#11', 'Brand#22') OR p_name IS NULL")
both("join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
both("join_merge", "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
both("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
both("join_full", "SELECT coalesce(a.k, b.k) AS k, a.k IS NULL AS added, b.k IS NULL AS deleted FROM (SELECT c_custkey AS k FROM customer WHERE c_custkey < 100) a FULL JOIN (SELECT c_custkey AS k FROM customer WHERE c_custkey BETWEEN 50 AND 120) b ON a.k = b.k")
both("semi_anti", "SELECT 'semi' AS kind, count(*) AS n FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) UNION ALL SELECT 'anti', count(*) FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
both("aggregate", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q, round(avg(l_discount), 6) AS d, min(l_tax) AS t FROM lineitem GROUP BY l_returnflag, l_linestatus")
both("aggregate_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY o_orderstatus")
both("aggregate_filter", "SELECT event_type, count(*) FILTER (WHERE value > 50) AS big, count(*) AS n FROM events GROUP BY event_type")
both("cube", "SELECT coalesce(o_orderstatus, '*') AS s, coalesce(o_orderpriority, '*') AS p, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
both("rollup", "SELECT coalesce(c_mktsegment, '*') AS s, coalesce(c_nationkey, -1) AS k, count(*) AS n FROM customer GROUP BY ROLLUP (c_mktsegment, c_nationkey)")
both("grouping_sets", "SELECT l_returnflag AS f, l_linestatus AS s, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
both("max_by", "SELECT o_custkey, max_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS best FROM orders GROUP BY o_custkey", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS best FROM orders GROUP BY o_custkey")
both("top_per_group", "SELECT * FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
both("window_ranks", "SELECT c_custkey, rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS r, dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS d, ntile(3) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS t FROM customer")
both("window_lag", "SELECT event_id, coalesce(lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1) AS before, coalesce(lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1) AS after FROM events")
both("window_running", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS s FROM events")
both("sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
both("union_all", "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
both("intersect", "SELECT c_nationkey AS k FROM customer WHERE c_custkey < 30 INTERSECT SELECT s_nationkey FROM supplier")
both("except", "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier WHERE s_suppkey < 20")
both("strings", "SELECT p_partkey, upper(p_name) AS u, length(p_type) AS n, substring(p_brand, 1, 3) AS b, md5(p_name) AS h FROM part")
both("dates", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m FROM orders")
both("math", "SELECT l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) AS s, greatest(l_discount, l_tax) AS g, l_orderkey % 7 AS m FROM lineitem")
both("json", "SELECT event_id, get_json_object(props, '$.page') AS page FROM events", "SELECT event_id, json_extract_string(props, '$.page') AS page FROM events")
both("arrays", "SELECT vec_id, size(filter(embedding, x -> x > 0)) AS positive, round(aggregate(transform(embedding, x -> CAST(x AS DOUBLE)), 0D, (a, b) -> a + b), 5) AS total FROM embeddings", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, round(list_sum(CAST(embedding AS DOUBLE[])), 5) AS total FROM embeddings")
both("explode", "SELECT label, pos, round(avg(CAST(x AS DOUBLE)), 6) AS m FROM embeddings LATERAL VIEW posexplode(embedding) t AS pos, x GROUP BY label, pos", "SELECT label, CAST(i - 1 AS INTEGER) AS pos, round(avg(CAST(embedding[i] AS DOUBLE)), 6) AS m FROM embeddings, range(1, 65) t(i) GROUP BY label, i")
both("subquery_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
both("subquery_correlated", "SELECT s_suppkey FROM supplier s WHERE s_acctbal >= (SELECT max(s_acctbal) FROM supplier t WHERE t.s_nationkey = s.s_nationkey)")
both("cte", "WITH big AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT n, count(*) AS customers FROM big GROUP BY n")
both("sample_hash", "SELECT c_custkey FROM customer WHERE c_custkey % 10 = 3")
both("lateral_topk", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")
both("pivot", "SELECT * FROM (SELECT event_type, user_id % 3 AS u FROM events) PIVOT (count(*) FOR u IN (0 AS a, 1 AS b, 2 AS c))", "SELECT event_type, count(*) FILTER (WHERE user_id % 3 = 0) AS a, count(*) FILTER (WHERE user_id % 3 = 1) AS b, count(*) FILTER (WHERE user_id % 3 = 2) AS c FROM events GROUP BY event_type")


@query("rel_asof_join_whole", "SELECT o.o_orderkey, max(e.ts) AS ts FROM (SELECT o_orderkey, o_custkey, TIMESTAMP '2024-01-10 00:00:00' + INTERVAL 1 HOUR * CAST(o_orderkey % 400 AS INTEGER) AS at FROM orders) o LEFT JOIN events e ON e.user_id = o.o_custkey % 150 AND e.ts <= o.at GROUP BY o.o_orderkey")
def rel_asof_join_whole(spark, sf):
    return asof_join(read(spark, sf, "orders"), read(spark, sf, "events"))


def asof_join(orders, events):
    """Latest event of a user at or before each order's hour: one union, one window, no pairs."""
    start = F.lit("2024-01-10 00:00:00").cast("timestamp")
    at = (start.cast("long") + (F.col("o_orderkey") % 400) * 3600).cast("timestamp")
    left = orders.select("o_orderkey", (F.col("o_custkey") % 150).alias("u"), at.alias("t"), F.lit(1).alias("side"), F.lit(None).cast("timestamp").alias("ts"))
    right = events.select(F.lit(None).cast("long").alias("o_orderkey"), F.col("user_id").alias("u"), F.col("ts").cast("timestamp").alias("t"), F.lit(0).alias("side"), F.col("ts").cast("timestamp").alias("ts"))
    w = Window.partitionBy("u").orderBy("t", "side").rowsBetween(Window.unboundedPreceding, 0)
    return left.unionByName(right).withColumn("ts", F.last("ts", ignorenulls=True).over(w)).filter("side = 1").select("o_orderkey", F.col("ts").cast("timestamp_ntz").alias("ts"))


@query("rel_range_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def rel_range_join(spark, sf):
    """Purchases within six hours of a view: hour-band keys make the range an equality with two bands a row."""
    e = read(spark, sf, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    band = 6 * 3600 * 1_000_000
    a = e.filter("event_type = 'view'").select(F.col("event_id").alias("a"), "user_id", F.col("s").alias("sa"), F.explode(F.array(F.floor(F.col("s") / band), F.floor(F.col("s") / band) + 1)).alias("band"))
    b = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("b"), "user_id", F.col("s").alias("sb"), F.floor(F.col("s") / band).alias("band"))
    return a.join(b, ["user_id", "band"]).filter((F.col("sb") >= F.col("sa")) & (F.col("sb") <= F.col("sa") + band)).select("a", "b")


@query("rel_sessions", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w > INTERVAL 12 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) SELECT user_id, CAST(sum(new) AS BIGINT) AS sessions FROM g GROUP BY user_id")
def rel_sessions(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = read(spark, sf, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    new = F.when(F.lag("s").over(w).isNull() | (F.col("s") - F.lag("s").over(w) > 12 * 3600 * 1_000_000), 1).otherwise(0)
    return e.withColumn("new", new).groupBy("user_id").agg(F.sum("new").alias("sessions"))


@query("rel_bitmap", "SELECT label, count(DISTINCT vec_id) AS n FROM embeddings GROUP BY label")
def rel_bitmap(spark, sf):
    e = read(spark, sf, "embeddings").select("label", F.bitmap_bucket_number("vec_id").alias("b"), F.bitmap_bit_position("vec_id").alias("p"))
    return e.groupBy("label", "b").agg(F.bitmap_count(F.bitmap_construct_agg("p")).alias("n")).groupBy("label").agg(F.sum("n").alias("n"))


for _fmt in ("csv", "json", "orc"):

    @query(f"rel_source_{_fmt}", "SELECT c_mktsegment, count(*) AS n, round(sum(c_acctbal), 2) AS b FROM customer GROUP BY c_mktsegment")
    def _source(spark, sf, fmt=_fmt):
        df = read(spark, sf, "customer")
        path = f"{warehouse(spark)}/{fmt}"
        df.write.format(fmt).save(path)
        return spark.read.schema(df.schema).format(fmt).load(path).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("b"))


@query("derived_ndv", "SELECT count(DISTINCT o_custkey) AS exact, true AS sketch_near FROM orders")
def derived_ndv(spark, sf):
    """An exact count beside a sketch that goes through a blob of the container."""
    from ..sources.container import DERIVED, Blob, read_blob, read_footer, write_container

    o = read(spark, sf, "orders")
    row = o.agg(F.countDistinct("o_custkey").alias("n"), F.hll_sketch_agg("o_custkey").alias("s")).first()
    path = f"{warehouse(spark)}/d.side"
    write_container(path, [Blob(DERIVED, bytes(row["s"]), properties={"kind": "hll", "column": "o_custkey"})])
    held = read_blob(path, read_footer(path).blobs[0])
    est = spark.createDataFrame([(bytearray(held),)], "s binary").select(F.hll_sketch_estimate("s")).first()[0]
    return spark.createDataFrame([(row["n"], abs(est - row["n"]) <= 0.05 * row["n"])], "exact long, sketch_near boolean")


@query("derived_materialized_agg", "SELECT o_orderstatus, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY o_orderstatus")
def derived_materialized_agg(spark, sf):
    import json

    from ..sources.container import DERIVED, Blob, read_blob, read_footer, write_container

    rows = read(spark, sf, "orders").groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total")).collect()
    path = f"{warehouse(spark)}/d.side"
    write_container(path, [Blob(DERIVED, json.dumps([r.asDict() for r in rows]).encode(), codec="zstd")])
    held = json.loads(read_blob(path, read_footer(path).blobs[0]))
    return spark.createDataFrame([(r["o_orderstatus"], r["n"], r["total"]) for r in held], "o_orderstatus string, n long, total double")
