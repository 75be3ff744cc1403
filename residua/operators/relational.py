"""The relational operators around the flow methods, one query each, with the SQL that says the same."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..functions.scalar import bounded, bounded_udf, host, state_label
from ..lineage import folder
from ..sources.tables import read, read_edges, write_edges

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def n_rows():
    return F.count(F.lit(1))


def op(sql: str | None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


@op("SELECT l_orderkey, l_suppkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1996-02-01'")
def op_scan_prune(s, d):
    return read(s, d, "lineitem", "l_orderkey", "l_suppkey", "l_quantity", "l_shipdate").where("l_shipdate >= timestamp_ntz'1996-01-01' and l_shipdate < timestamp_ntz'1996-02-01'").drop("l_shipdate")


@op("SELECT p_partkey, CAST(floor(p_retailprice * 100) AS BIGINT) AS cap FROM part")
def op_project_cast(s, d):
    return read(s, d, "part", "p_partkey", "p_retailprice").select("p_partkey", F.floor(F.col("p_retailprice") * 100).cast("long").alias("cap"))


@op("SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus IN ('O','F') AND o_orderpriority LIKE '1%' AND o_totalprice BETWEEN 1000 AND 200000")
def op_filter_compound(s, d):
    o = read(s, d, "orders")
    return o.where(F.col("o_orderstatus").isin("O", "F") & F.col("o_orderpriority").like("1%") & F.col("o_totalprice").between(1000, 200000)).select("o_orderkey", "o_custkey")


@op("SELECT page_id, url FROM pages WHERE regexp_matches(url, '^https?://[a-m]')")
def op_filter_regex(s, d):
    return read(s, d, "pages", "page_id", "url").where(F.col("url").rlike("^https?://[a-m]"))


@op("SELECT l_suppkey, o_custkey, CAST(sum(l_quantity) AS BIGINT) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE c_nationkey = 3 GROUP BY ALL")
def op_join_inner(s, d):
    c = read(s, d, "customer", "c_custkey", "c_nationkey").where("c_nationkey = 3")
    o = read(s, d, "orders", "o_orderkey", "o_custkey").join(c, F.col("o_custkey") == F.col("c_custkey"))
    line = read(s, d, "lineitem", "l_orderkey", "l_suppkey", "l_quantity")
    return line.join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("l_suppkey", "o_custkey").agg(F.sum("l_quantity").cast("long").alias("q"))


@op("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def op_join_broadcast(s, d):
    n = read(s, d, "nation", "n_nationkey", "n_name", "n_regionkey").join(F.broadcast(read(s, d, "region", "r_regionkey", "r_name")), F.col("n_regionkey") == F.col("r_regionkey"))
    return read(s, d, "customer", "c_custkey", "c_nationkey").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


@op("SELECT s_nationkey, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def op_join_merge(s, d):
    return read(s, d, "lineitem", "l_suppkey").join(read(s, d, "supplier", "s_suppkey", "s_nationkey").hint("merge"), F.col("l_suppkey") == F.col("s_suppkey")).groupBy("s_nationkey").agg(n_rows().alias("n"))


@op("SELECT n_nationkey, CAST(count(c_custkey) AS BIGINT) AS n FROM nation LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1")
def op_join_left(s, d):
    c = read(s, d, "customer", "c_nationkey").groupBy("c_nationkey").agg(n_rows().alias("n"))
    return read(s, d, "nation", "n_nationkey").join(c, F.col("c_nationkey") == F.col("n_nationkey"), "left").select("n_nationkey", F.coalesce("n", F.lit(0)).alias("n"))


FORWARD = "SELECT s_nationkey AS a, c_nationkey AS b, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE s_nationkey < 6 AND c_nationkey < 6 GROUP BY 1, 2"


def forward(s, d, below=None):
    c, p = read(s, d, "customer", "c_custkey", "c_nationkey"), read(s, d, "supplier", "s_suppkey", "s_nationkey")
    if below is not None:
        c, p = c.where(F.col("c_nationkey") < below), p.where(F.col("s_nationkey") < below)
    x = read(s, d, "lineitem", "l_orderkey", "l_suppkey").join(read(s, d, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    x = x.join(c, F.col("o_custkey") == F.col("c_custkey")).join(p, F.col("l_suppkey") == F.col("s_suppkey"))
    return x.groupBy(F.col("s_nationkey").alias("a"), F.col("c_nationkey").alias("b")).agg(n_rows().alias("n"))


def both_ways(f):
    g = f.select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("n").alias("n_in"))
    return f.withColumnRenamed("n", "n_out").join(g, ["a", "b"], "full").select("a", "b", F.coalesce("n_out", F.lit(0)).alias("n_out"), F.coalesce("n_in", F.lit(0)).alias("n_in"))


FULL = "SELECT coalesce(x.a, y.b) AS a, coalesce(x.b, y.a) AS b, coalesce(x.n, 0) AS n_out, coalesce(y.n, 0) AS n_in FROM f x FULL JOIN f y ON x.a = y.b AND x.b = y.a"


@op(f"WITH f AS ({FORWARD}) {FULL}")
def op_join_full(s, d):
    return both_ways(forward(s, d, 6))


FORWARD_ALL = "SELECT s_nationkey AS a, c_nationkey AS b, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2"


@op(f"WITH f AS ({FORWARD_ALL}) {FULL}")
def op_join_full_nations(s, d):
    return both_ways(forward(s, d))


@op("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def op_join_semi(s, d):
    return read(s, d, "customer", "c_custkey").join(read(s, d, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@op("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def op_join_anti(s, d):
    return read(s, d, "customer", "c_custkey").join(read(s, d, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@op("SELECT r_name, seg FROM region, (SELECT DISTINCT c_mktsegment AS seg FROM customer)")
def op_join_cross(s, d):
    return read(s, d, "region", "r_name").crossJoin(read(s, d, "customer", "c_mktsegment").distinct().select(F.col("c_mktsegment").alias("seg")))


@op("SELECT a.s_suppkey AS x, b.s_suppkey AS y FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal > b.s_acctbal + 1000")
def op_join_theta(s, d):
    a = read(s, d, "supplier", "s_suppkey", "s_nationkey", "s_acctbal")
    b = a.select(F.col("s_suppkey").alias("y"), "s_nationkey", F.col("s_acctbal").alias("other"))
    return a.join(b, "s_nationkey").where("s_acctbal > other + 1000").select(F.col("s_suppkey").alias("x"), "y")


@op("SELECT event_id, CAST(floor(value / 25) AS BIGINT) AS band FROM events WHERE value >= 0 AND floor(value / 25) < 8")
def op_join_range(s, d):
    """Bands of values as a bucketised range join: one equi key, then the exact bounds."""
    bands = s.range(8).select(F.col("id").alias("band"), (F.col("id") * 25).cast("double").alias("low"))
    e = read(s, d, "events", "event_id", "value").withColumn("bucket", F.floor(F.col("value") / 25))
    return e.join(bands, F.col("bucket") == F.col("band")).where("value >= low and value < low + 25").select("event_id", "band")


@op("SELECT p.event_id, max_by(e.event_id, struct_pack(a := e.ts, b := e.event_id)) AS before FROM events p LEFT JOIN events e ON e.user_id = p.user_id AND e.event_type <> 'purchase' AND (e.ts < p.ts OR (e.ts = p.ts AND e.event_id < p.event_id)) WHERE p.event_type = 'purchase' GROUP BY 1")
def op_join_asof(s, d):
    """Latest other event of a user before each purchase: one sort by user, no pair of rows is formed."""
    e = read(s, d, "events", "event_id", "ts", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    other = F.when(F.col("event_type") != "purchase", F.col("event_id"))
    return e.withColumn("before", F.last(other, ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "before")


@op("SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def op_join_interval(s, d):
    e = read(s, d, "events", "event_id", "ts", "user_id", "event_type")
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("ts").alias("at"), "user_id")
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "ts", "user_id")
    return c.join(p, "user_id").where("ts >= at and ts <= at + interval 1 hour").select("click", "purchase")


@op("WITH u AS (SELECT DISTINCT user_id, event_type FROM events) SELECT a.event_type AS x, b.event_type AS y, count(*) AS n FROM u a JOIN u b USING (user_id) WHERE a.event_type < b.event_type GROUP BY 1, 2")
def op_join_self(s, d):
    u = read(s, d, "events", "user_id", "event_type").distinct()
    return u.select("user_id", F.col("event_type").alias("x")).join(u.select("user_id", F.col("event_type").alias("y")), "user_id").where("x < y").groupBy("x", "y").agg(n_rows().alias("n"))


@op("SELECT l_suppkey, CAST(sum(l_quantity) AS BIGINT) AS cap FROM lineitem GROUP BY 1")
def op_agg_sum(s, d):
    return read(s, d, "lineitem", "l_suppkey", "l_quantity").groupBy("l_suppkey").agg(F.sum("l_quantity").cast("long").alias("cap"))


@op("SELECT l_suppkey, min_by(l_partkey, struct_pack(a := l_quantity, b := l_partkey)) AS low FROM lineitem GROUP BY 1")
def op_agg_argmin(s, d):
    return read(s, d, "lineitem", "l_suppkey", "l_partkey", "l_quantity").groupBy("l_suppkey").agg(F.min(F.struct("l_quantity", "l_partkey"))["l_partkey"].alias("low"))


@op("SELECT l_suppkey, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1")
def op_agg_distinct(s, d):
    return read(s, d, "lineitem", "l_suppkey", "l_partkey").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("n"))


@op(None)
def op_agg_approx(s, d):
    return read(s, d, "lineitem", "l_suppkey", "l_partkey").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey").alias("n"))


GEO = "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY "


def geo(s, d):
    return op_join_broadcast(s, d)


@op(GEO + "ROLLUP (r_name, n_name)")
def op_agg_rollup(s, d):
    return geo(s, d).rollup("r_name", "n_name").agg(n_rows().alias("n"))


@op(GEO + "CUBE (r_name, n_name)")
def op_agg_cube(s, d):
    return geo(s, d).cube("r_name", "n_name").agg(n_rows().alias("n"))


@op(GEO + "GROUPING SETS ((r_name), (n_name))")
def op_agg_sets(s, d):
    geo(s, d).createOrReplaceTempView("residua_geo")
    return s.sql("SELECT r_name, n_name, count(*) AS n FROM residua_geo GROUP BY GROUPING SETS ((r_name), (n_name))")


@op("SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY 1")
def op_agg_pivot(s, d):
    return read(s, d, "orders", "o_orderpriority", "o_orderstatus").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(n_rows()).select("o_orderpriority", *[F.coalesce(F.col(c), F.lit(0)).alias(c.lower()) for c in "FOP"])


@op("WITH g AS (SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1) SELECT quantile_cont(n, 0.5) AS p50, quantile_cont(n, 0.9) AS p90 FROM g")
def op_agg_percentile(s, d):
    g = read(s, d, "lineitem", "l_suppkey").groupBy("l_suppkey").agg(n_rows().alias("n"))
    return g.agg(F.percentile("n", 0.5).alias("p50"), F.percentile("n", 0.9).alias("p90"))


@op("WITH g AS (SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1) SELECT CAST(floor(log2(n)) AS BIGINT) AS bin, count(*) AS n FROM g GROUP BY 1")
def op_agg_histogram(s, d):
    g = read(s, d, "lineitem", "l_partkey").groupBy("l_partkey").agg(n_rows().alias("n"))
    return g.groupBy(F.floor(F.log2("n")).cast("long").alias("bin")).agg(n_rows().alias("n"))


@op("SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 40")
def op_agg_having(s, d):
    return read(s, d, "lineitem", "l_partkey").groupBy("l_partkey").agg(n_rows().alias("n")).where("n > 40")


PAIRS = "WITH a AS (SELECT l_suppkey AS src, l_partkey AS dst, CAST(sum(l_quantity) AS BIGINT) AS cap FROM lineitem GROUP BY 1, 2) "


def pairs(s, d):
    return read(s, d, "lineitem", "l_suppkey", "l_partkey", "l_quantity").groupBy(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst")).agg(F.sum("l_quantity").cast("long").alias("cap"))


def by_cap():
    return Window.partitionBy("src").orderBy(F.desc("cap"), "dst")


@op(PAIRS + "SELECT src, dst, CAST(rank() OVER (PARTITION BY src ORDER BY cap DESC) AS INTEGER) AS r FROM a")
def op_win_rank(s, d):
    return pairs(s, d).select("src", "dst", F.rank().over(Window.partitionBy("src").orderBy(F.desc("cap"))).alias("r"))


@op(PAIRS + "SELECT src, dst, CAST(row_number() OVER (PARTITION BY src ORDER BY cap DESC, dst) AS INTEGER) AS r FROM a")
def op_win_rownum(s, d):
    return pairs(s, d).select("src", "dst", F.row_number().over(by_cap()).alias("r"))


@op(PAIRS + "SELECT src, dst, CAST(ntile(4) OVER (PARTITION BY src ORDER BY cap DESC, dst) AS INTEGER) AS q FROM a")
def op_win_ntile(s, d):
    return pairs(s, d).select("src", "dst", F.ntile(4).over(by_cap()).alias("q"))


@op("SELECT event_id, lag(user_id) OVER w AS before, lead(user_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id)")
def op_win_lead_lag(s, d):
    w = Window.partitionBy("event_type").orderBy("ts", "event_id")
    return read(s, d, "events", "event_id", "ts", "user_id", "event_type").select("event_id", F.lag("user_id").over(w).alias("before"), F.lead("user_id").over(w).alias("after"))


@op(PAIRS + "SELECT src, dst, CAST(sum(cap) OVER (PARTITION BY src ORDER BY cap DESC, dst ROWS UNBOUNDED PRECEDING) AS BIGINT) AS run FROM a")
def op_win_running(s, d):
    return pairs(s, d).select("src", "dst", F.sum("cap").over(by_cap().rowsBetween(Window.unboundedPreceding, 0)).alias("run"))


@op("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def op_win_range(s, d):
    e = read(s, d, "events", "event_id", "ts", "user_id").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", n_rows().over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)).alias("n"))


@op(PAIRS + "SELECT src, dst, cap FROM a ORDER BY cap DESC, src, dst LIMIT 25")
def op_sort_limit(s, d):
    return pairs(s, d).orderBy(F.desc("cap"), "src", "dst").limit(25)


@op(PAIRS + "SELECT src, dst, cap FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY cap DESC, dst) AS r FROM a) WHERE r <= 3")
def op_topk_per_group(s, d):
    return pairs(s, d).withColumn("r", F.row_number().over(by_cap())).where("r <= 3").drop("r")


@op(PAIRS + "SELECT src, dst, cap FROM a ORDER BY cap DESC, src, dst LIMIT 10 OFFSET 20")
def op_offset(s, d):
    return pairs(s, d).orderBy(F.desc("cap"), "src", "dst").offset(20).limit(10)


SETS = "WITH a AS (SELECT o_custkey AS c FROM orders WHERE o_orderstatus = 'F'), b AS (SELECT o_custkey AS c FROM orders WHERE o_orderstatus = 'O') SELECT c FROM a {} SELECT c FROM b"


def two(s, d):
    o = read(s, d, "orders", "o_custkey", "o_orderstatus")
    return o.where("o_orderstatus = 'F'").select(F.col("o_custkey").alias("c")), o.where("o_orderstatus = 'O'").select(F.col("o_custkey").alias("c"))


@op(SETS.format("UNION"))
def op_set_union(s, d):
    a, b = two(s, d)
    return a.union(b).distinct()


@op(SETS.format("INTERSECT ALL"))
def op_set_intersect(s, d):
    a, b = two(s, d)
    return a.intersectAll(b)


@op(SETS.format("EXCEPT"))
def op_set_except(s, d):
    a, b = two(s, d)
    return a.subtract(b)


@op(PAIRS + "SELECT src, dst FROM a WHERE (src * 7919 + dst * 104729) % 1000003 % 100 < 5")
def op_sample_hash(s, d):
    return pairs(s, d).where((F.col("src") * 7919 + F.col("dst") * 104729) % 1_000_003 % 100 < 5).select("src", "dst")


@op("SELECT regexp_extract(url, '://([^/]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def op_str_host(s, d):
    return read(s, d, "pages", "url").groupBy(host(F.col("url")).alias("host")).agg(n_rows().alias("n"))


@op("SELECT c_custkey, lower(trim(c_mktsegment)) AS seg, CAST(length(c_name) AS INTEGER) AS n FROM customer")
def op_str_clean(s, d):
    return read(s, d, "customer", "c_custkey", "c_mktsegment", "c_name").select("c_custkey", F.lower(F.trim("c_mktsegment")).alias("seg"), F.length("c_name").alias("n"))


@op("SELECT CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY 1")
def op_date_trunc(s, d):
    return read(s, d, "events", "ts").groupBy(F.to_date(F.date_trunc("day", F.col("ts").cast("timestamp"))).alias("day")).agg(n_rows().alias("n"))


@op("SELECT date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS lag, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def op_date_diff(s, d):
    j = read(s, d, "lineitem", "l_orderkey", "l_shipdate").join(read(s, d, "orders", "o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy(F.datediff(F.to_date("l_shipdate"), F.to_date("o_orderdate")).cast("long").alias("lag")).agg(n_rows().alias("n"))


@op("SELECT p_partkey, CAST(greatest(1, least(90, CAST(floor(p_retailprice) AS BIGINT) % 100)) AS BIGINT) AS cap FROM part")
def op_math_scale(s, d):
    return read(s, d, "part", "p_partkey", "p_retailprice").select("p_partkey", bounded(F.col("p_retailprice"), 1, 90, 100).alias("cap"))


@op(ORACLES["op_math_scale"])
def op_udf_pandas(s, d):
    return read(s, d, "part", "p_partkey", "p_retailprice").select("p_partkey", bounded_udf(1, 90, 100)("p_retailprice").alias("cap"))


@op("SELECT vec_id, CAST(len(embedding) AS INTEGER) AS n, CAST(round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS DOUBLE) AS norm FROM embeddings")
def op_array_ops(s, d):
    return read(s, d, "embeddings", "vec_id", "embedding").select("vec_id", F.size("embedding").alias("n"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("norm"))


@op("SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS target FROM pages")
def op_explode(s, d):
    return read(s, d, "pages", "page_id", "html").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("target"))


@op("SELECT n_regionkey, CAST(count(*) AS INTEGER) AS n, CAST(max(n_nationkey) AS INTEGER) AS top FROM nation GROUP BY 1")
def op_map_ops(s, d):
    m = read(s, d, "nation", "n_regionkey", "n_nationkey", "n_name").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_name", "n_nationkey"))).alias("m"))
    return m.select("n_regionkey", F.size(F.map_keys("m")).alias("n"), F.array_max(F.map_values("m")).alias("top"))


@op("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def op_json_get(s, d):
    return read(s, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@op("WITH g AS (SELECT n_nationkey AS id, (SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) * 10 - (SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) AS e FROM nation) SELECT id, CASE WHEN e > 0 THEN 'overflow' WHEN e < 0 THEN 'deficit' ELSE 'balanced' END AS state FROM g")
def op_case(s, d):
    a = read(s, d, "supplier", "s_nationkey").groupBy(F.col("s_nationkey").alias("id")).agg(n_rows().alias("a"))
    b = read(s, d, "customer", "c_nationkey").groupBy(F.col("c_nationkey").alias("id")).agg(n_rows().alias("b"))
    g = read(s, d, "nation").select(F.col("n_nationkey").alias("id")).join(a, "id", "left").join(b, "id", "left")
    return g.select("id", state_label(F.coalesce("a", F.lit(0)) * 10 - F.coalesce("b", F.lit(0))).alias("state"))


@op("WITH d AS (SELECT n_regionkey AS r, n_nationkey AS n, count(c_custkey) AS d FROM nation LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1, 2) SELECT r, CAST(least((sum(d) * (2 + r)) // 4, sum(least(d, 1 + (d * (1 + n % 3)) // 2))) AS BIGINT) AS value FROM d GROUP BY r")
def op_udaf(s, d):
    """Exact value of one small network for each region, solved inside the group."""

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        from residua.reference import sequential_push_relabel

        r = int(pdf.r.iloc[0])
        arcs = [(-1, 100, int(pdf.d.sum()) * (2 + r) // 4)] + [(100, int(n), int(x)) for n, x in zip(pdf.n, pdf.d, strict=True)] + [(int(n), -2, 1 + int(x) * (1 + int(n) % 3) // 2) for n, x in zip(pdf.n, pdf.d, strict=True)]
        return pd.DataFrame({"r": [r], "value": [sequential_push_relabel(arcs, -1, -2)]})

    c = read(s, d, "customer", "c_nationkey").groupBy("c_nationkey").agg(n_rows().alias("d"))
    g = read(s, d, "nation").join(c, F.col("n_nationkey") == F.col("c_nationkey"), "left").select(F.col("n_regionkey").alias("r"), F.col("n_nationkey").alias("n"), F.coalesce("d", F.lit(0)).alias("d"))
    return g.groupBy("r").applyInPandas(solve, "r int, value long")


@op("SELECT c_custkey AS src, (c_custkey * 3 + j.range) % 10 AS dst FROM customer, range(3) j")
def op_udtf(s, d):
    """Neighbours of every customer's vertex, a row each."""

    @udtf(returnType="src: bigint, dst: bigint")
    class Near:
        def eval(self, src: int):
            for j in range(3):
                to = None if src is None else src * 3 + j
                yield src, to if to is None else to % 10 if to >= 0 else -(-to % 10)

    s.udtf.register("residua_near", Near)
    read(s, d, "customer", "c_custkey").createOrReplaceTempView("residua_vertices")
    return s.sql("SELECT n.src, n.dst FROM residua_vertices v, LATERAL residua_near(v.c_custkey) n")


REACH = "SELECT DISTINCT s_nationkey AS u, c_nationkey AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE (s_nationkey * 5 + c_nationkey) % 9 = 0"


@op(f"WITH RECURSIVE e AS ({REACH}), r(id, hop) AS (SELECT 3, 0 UNION SELECT e.v, r.hop + 1 FROM r JOIN e ON e.u = r.id WHERE r.hop < 3) SELECT DISTINCT id FROM r")
def op_cte_reach(s, d):
    line = read(s, d, "lineitem", "l_orderkey", "l_suppkey").join(read(s, d, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(read(s, d, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(read(s, d, "supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    e = line.where("(s_nationkey * 5 + c_nationkey) % 9 = 0").select(F.col("s_nationkey").alias("u"), F.col("c_nationkey").alias("v")).distinct()
    at = s.range(1).select(F.lit(3).alias("id"))
    for _ in range(3):
        at = at.unionByName(at.join(e, F.col("id") == F.col("u")).select(F.col("v").alias("id"))).distinct()
    return at


@op(PAIRS + "SELECT src, dst FROM a x WHERE cap > (SELECT avg(cap) FROM a y WHERE y.src = x.src)")
def op_subquery_corr(s, d):
    pairs(s, d).createOrReplaceTempView("residua_pairs")
    return s.sql("SELECT src, dst FROM residua_pairs x WHERE cap > (SELECT avg(cap) FROM residua_pairs y WHERE y.src = x.src)")


def trip(fmt):
    def run(s, d):
        path = folder(s)
        write_edges(pairs(s, d), path, fmt)
        return read_edges(s, path, fmt)[0]

    run.__name__ = f"op_write_read_{fmt}"
    return run


for _fmt in ("parquet", "csv", "json"):
    op(PAIRS + "SELECT src, dst, cap FROM a")(trip(_fmt))
