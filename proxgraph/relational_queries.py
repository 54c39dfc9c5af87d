"""Driver queries of the relational and streaming operators, with their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .operators import relational
from .sources.fixtures import nearest, table
from .streaming import edges as streams

QUERIES: dict[str, Callable] = {}
SQL: dict[str, str] = {}


def _add(sql: str | None):
    def put(run: Callable) -> Callable:
        QUERIES[run.__name__] = run
        if sql is not None:
            SQL[run.__name__] = sql
        return run

    return put


@_add("SELECT c_custkey, c_name FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def rel_semi_join(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").where("o_totalprice > 300000").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, d, "customer").join(o, "c_custkey", "left_semi").select("c_custkey", "c_name")


@_add("SELECT count(*) AS without_lines FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def rel_anti_join(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"))
    return table(spark, d, "orders").join(li, "o_orderkey", "left_anti").agg(F.count("*").alias("without_lines"))


@_add("SELECT n_name, count(c_custkey) AS customers, round(coalesce(sum(c_acctbal), 0), 2) AS balance FROM nation LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY n_name")
def rel_left_join(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "customer").select(F.col("c_nationkey").alias("n_nationkey"), "c_custkey", "c_acctbal")
    return F.broadcast(table(spark, d, "nation")).join(c, "n_nationkey", "left").groupBy("n_name").agg(F.count("c_custkey").alias("customers"), F.round(F.coalesce(F.sum("c_acctbal"), F.lit(0)), 2).alias("balance"))


@_add("SELECT coalesce(c.k, s.k) AS nation, coalesce(c.n, 0) AS customers, coalesce(s.n, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) s ON c.k = s.k")
def rel_full_join(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("c"))
    s = table(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("s"))
    return c.join(s, "nation", "full").select("nation", F.coalesce("c", F.lit(0)).cast("long").alias("customers"), F.coalesce("s", F.lit(0)).cast("long").alias("suppliers"))


@_add("SELECT e.event_id, (SELECT max(p.event_id) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts = (SELECT max(q.ts) FROM events q WHERE q.user_id = e.user_id AND q.event_type = 'purchase' AND q.ts <= e.ts)) AS last_purchase FROM events e WHERE e.event_type = 'click'")
def rel_asof_join(spark: SparkSession, d: str) -> DataFrame:
    """The latest purchase of the same user at each click."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    bought = e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("event_id").alias("purchase"))
    out = relational.asof_join(e.where("event_type = 'click'").drop("event_type"), bought, "user_id", "ts", ["purchase"])
    return out.select("event_id", F.col("asof_purchase").alias("last_purchase"))


@_add("SELECT count(*) AS pairs, count(DISTINCT a.event_id) AS followers FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND epoch(a.ts) - epoch(b.ts) BETWEEN 0 AND 7200")
def rel_interval_join(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of events of a user within two hours."""
    e = table(spark, d, "events").select("event_id", "user_id", (F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).alias("at"))
    out = relational.interval_join(e, e.select(F.col("event_id").alias("other"), "user_id", F.col("at").alias("other_at")), "user_id", "at", "other_at", 7200, 7200)
    return out.where("event_id <> other").agg(F.count("*").alias("pairs"), F.count_distinct("event_id").alias("followers"))


@_add("WITH c AS (SELECT c_custkey, (sum(c_acctbal) OVER (ORDER BY c_custkey) - c_acctbal) / sum(c_acctbal) OVER () AS lo, sum(c_acctbal) OVER (ORDER BY c_custkey) / sum(c_acctbal) OVER () AS hi FROM customer WHERE c_acctbal > 0), p AS (SELECT unnest(range(1000)) AS i) SELECT i, c_custkey FROM p JOIN c ON (i + 0.5) / 1000 >= lo AND (i + 0.5) / 1000 < hi")
def rel_range_join(spark: SparkSession, d: str) -> DataFrame:
    """A thousand evenly spaced draws from customers by balance: inverse of the cumulative distribution."""
    c = table(spark, d, "customer").where("c_acctbal > 0").select("c_custkey", "c_acctbal")
    total = c.agg(F.sum("c_acctbal")).first()[0]
    run = relational.cumulative(c, "c_acctbal", ["c_custkey"], F.floor(F.col("c_custkey") / 1000))
    ranges = run.select("c_custkey", ((F.col("running") - F.col("c_acctbal")) / total).alias("lo"), (F.col("running") / total).alias("hi"))
    points = spark.range(1000).select(F.col("id").alias("i"), ((F.col("id") + 0.5) / 1000).alias("x"))
    return relational.range_lookup(points, ranges, "x", "lo", "hi", 256).select("i", "c_custkey")


@_add("WITH e AS (SELECT DISTINCT o_custkey AS c, l_partkey AS p FROM lineitem JOIN orders ON o_orderkey = l_orderkey) SELECT a.p AS p, b.p AS q, count(*) AS shared FROM e a JOIN e b ON a.c = b.c AND a.p < b.p GROUP BY 1, 2 HAVING count(*) > 1")
def rel_common_neighbours(spark: SparkSession, d: str) -> DataFrame:
    """All pairs of parts that share two customers or more."""
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c"))
    e = table(spark, d, "lineitem").select("l_orderkey", F.col("l_partkey").alias("p")).join(o, "l_orderkey").select("c", "p")
    return relational.common_neighbours(e, "c", "p", "q")


@_add("SELECT n_regionkey AS region, c_mktsegment AS segment, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)")
def rel_rollup(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "customer").join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return c.rollup(F.col("n_regionkey").alias("region"), F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@_add("SELECT l_returnflag, l_linestatus, count(*) AS lines, round(avg(l_quantity), 6) AS quantity FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def rel_cube(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("lines"), F.round(F.avg("l_quantity"), 6).alias("quantity"))


@_add("SELECT o_orderstatus, o_orderpriority, count(*) AS orders FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def rel_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders")
    return o.groupingSets([[F.col("o_orderstatus")], [F.col("o_orderpriority")], []], F.col("o_orderstatus"), F.col("o_orderpriority")).agg(F.count("*").alias("orders"))


@_add("SELECT event_type, count(*) FILTER (dow = 0) AS d0, count(*) FILTER (dow = 6) AS d6 FROM (SELECT event_type, dayofweek(ts) AS dow FROM events) GROUP BY 1")
def rel_pivot(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").withColumn("dow", F.dayofweek("ts") - 1)
    return e.groupBy("event_type").pivot("dow", [0, 6]).agg(F.count(F.lit(1))).select("event_type", F.coalesce("0", F.lit(0)).cast("long").alias("d0"), F.coalesce("6", F.lit(0)).cast("long").alias("d6"))


@_add("SELECT min(value) AS lo, max(value) AS hi, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd, round(median(value), 6) AS mid, round(quantile_cont(value, 0.9), 6) AS p90, count(DISTINCT user_id) AS users, arg_max(event_id, (value, event_id)) AS top FROM events")
def rel_aggregates(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    return e.agg(F.min("value").alias("lo"), F.max("value").alias("hi"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev_samp("value"), 6).alias("sd"), F.round(F.median("value"), 6).alias("mid"), F.round(F.percentile("value", F.lit(0.9)), 6).alias("p90"), F.count_distinct("user_id").alias("users"), F.max_by("event_id", F.struct("value", "event_id")).alias("top"))


@_add("SELECT o_custkey, o_orderkey, pos FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS pos FROM orders) WHERE pos <= 3")
def rel_top_per_group(spark: SparkSession, d: str) -> DataFrame:
    return relational.top_per_group(table(spark, d, "orders"), ["o_custkey"], [F.desc("o_totalprice"), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey", "pos")


@_add("SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS q, round(percent_rank() OVER w, 6) AS pr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def rel_ranks(spark: SparkSession, d: str) -> DataFrame:
    w, v = Window.partitionBy("p_brand").orderBy("p_size"), Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")
    return table(spark, d, "part").select("p_partkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(v).cast("long").alias("q"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@_add("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS smooth, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def rel_moving_frames(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").withColumn("at", F.unix_micros(F.col("ts").cast("timestamp")) / 1e6)
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    span = Window.partitionBy("user_id").orderBy("at").rangeBetween(-3600, 0)
    return e.select("event_id", F.round(F.avg("value").over(rows), 6).alias("smooth"), F.count("*").over(span).alias("last_hour"))


@_add("SELECT o_orderkey, round(sum(o_totalprice) OVER (ORDER BY o_orderkey), 2) AS running FROM orders")
def rel_prefix_sum(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").select("o_orderkey", "o_totalprice")
    return relational.cumulative(o, "o_totalprice", ["o_orderkey"], F.floor(F.col("o_orderkey") / 1000)).select("o_orderkey", F.round("running", 2).alias("running"))


@_add("(SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL (SELECT 100 + n_nationkey FROM nation EXCEPT SELECT 100 + s_nationkey FROM supplier)")
def rel_set_operations(spark: SparkSession, d: str) -> DataFrame:
    c, s = table(spark, d, "customer").select(F.col("c_nationkey").alias("k")), table(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))
    left = table(spark, d, "nation").select((F.col("n_nationkey") + 100).alias("k")).subtract(s.select((F.col("k") + 100).alias("k")))
    return c.intersect(s).unionByName(left)


@_add("SELECT event_id, (props::JSON ->> '$.k')::BIGINT AS k FROM events WHERE (props::JSON ->> '$.k')::BIGINT BETWEEN 10 AND 20")
def rel_json(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return e.where(F.col("k").between(10, 20))


@_add("SELECT page_id, len(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1))::BIGINT AS links FROM pages")
def rel_regex(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "pages").select("page_id", F.size(F.expr("regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)")).cast("long").alias("links"))


@_add("SELECT a AS src, b AS dst, sim FROM (SELECT x.vec_id AS a, y.vec_id AS b, round(round(list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]), 9), 6) AS sim, row_number() OVER (PARTITION BY x.vec_id ORDER BY round(list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]), 9) DESC, y.vec_id) AS k FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) WHERE k <= 5")
def rel_nearest(spark: SparkSession, d: str) -> DataFrame:
    return nearest(table(spark, d, "embeddings"), 5).select("src", "dst", F.round("sim", 6).alias("sim"))


# streams: read to the end, then compared with the batch answer

_WIN = "SELECT epoch_us(date_trunc('day', ts)) AS start, event_type, count(*) AS events, round(sum(value), 6) AS total FROM events GROUP BY 1, 2"


@_add(_WIN)
def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    out = streams.run_to_end(streams.tumbling(streams.event_stream(spark, d)), "complete")
    return out.select(F.unix_micros("start").alias("start"), "event_type", "events", F.round("total", 6).alias("total"))


@_add("SELECT epoch_us(s) AS start, count(*) AS events FROM (SELECT unnest([w - INTERVAL 18 HOUR, w - INTERVAL 12 HOUR, w - INTERVAL 6 HOUR, w]) AS s, ts FROM (SELECT ts, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS w FROM events)) GROUP BY 1")
def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    out = streams.run_to_end(streams.sliding(streams.event_stream(spark, d)), "complete")
    return out.select(F.unix_micros("start").alias("start"), "events")


@_add("WITH g AS (SELECT user_id, ts, sum(CASE WHEN gap IS NULL OR gap >= INTERVAL 30 MINUTE THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM (SELECT user_id, ts, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS gap FROM events)) SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS events FROM g GROUP BY user_id, s")
def stream_sessions(spark: SparkSession, d: str) -> DataFrame:
    out = streams.run_to_end(streams.sessions(streams.event_stream(spark, d, closing="30 minutes")), "append")
    return out.select("user_id", F.unix_micros("start").alias("start"), "events")


@_add("SELECT count(*) AS events, count(DISTINCT event_id) AS ids FROM events")
def stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    """Every file is read twice; repeated events are dropped within the watermark."""
    return streams.run_to_end(streams.dedup(streams.event_stream(spark, d, copies=2)), "append").agg(F.count("*").alias("events"), F.count_distinct("event_id").alias("ids"))


@_add("SELECT src, dst, count(*) AS n FROM (SELECT user_id AS src, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL GROUP BY 1, 2")
def stream_transitions(spark: SparkSession, d: str) -> DataFrame:
    """Arcs from each event's user to the next one's of the same type, by a stateful operator."""
    return streams.run_to_end(streams.transitions(streams.event_stream(spark, d)), "append").groupBy("src", "dst").agg(F.count("*").alias("n"))
