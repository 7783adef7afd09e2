"""Registered queries of the relational, scalar, streaming and UDF operators, with their SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .functions import udfs
from .functions.curves import morton_sql
from .functions.hashing import DUCK, uid_hash
from .functions.keys import global_rank
from .operators import aggregates, joins
from .plans import medians
from .sources import io
from .sources.io import table
from .storage import folder
from .streaming import events as stream

ENTRIES: dict[str, tuple] = {}


def entry(sql: str | None):
    def keep(f):
        ENTRIES[f.__name__] = (f, sql)
        return f

    return keep


def _path(s) -> str:
    return folder(s, "files/table")


# Scans, sources, sinks


@entry("SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 400000")
def scan_prune(s, d):
    return table(s, d, "orders", ["o_orderkey", "o_totalprice"]).where("o_totalprice > 400000")


@entry("SELECT count(*) AS n FROM lineitem")
def scan_count(s, d):
    return io.stats(s, d, "lineitem")


@entry("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def roundtrip_csv(s, d):
    return io.roundtrip(table(s, d, "nation"), "csv", _path(s))


@entry("SELECT event_id, user_id, event_type, value FROM events")
def roundtrip_json(s, d):
    return io.roundtrip(table(s, d, "events", ["event_id", "user_id", "event_type", "value"]), "json", _path(s))


@entry("SELECT event_id, user_id, event_type, value FROM events")
def roundtrip_orc(s, d):
    return io.roundtrip(table(s, d, "events", ["event_id", "user_id", "event_type", "value"]), "orc", _path(s))


@entry("SELECT l_shipdate, l_orderkey, l_linenumber FROM lineitem")
def sorted_write_readback(s, d):
    path = _path(s)
    io.write_sorted(table(s, d, "lineitem", ["l_shipdate", "l_orderkey", "l_linenumber"]), path, 8, "l_shipdate")
    return s.read.parquet(path)


@entry("SELECT min(l_shipdate) AS low, max(l_shipdate) AS high, count(*) AS rows FROM lineitem")
def zone_map(s, d):
    path = _path(s)
    io.write_sorted(table(s, d, "lineitem", ["l_shipdate"]), path, 8, "l_shipdate")
    return io.zone_map(s, path, "l_shipdate").agg(F.min("low").alias("low"), F.max("high").alias("high"), F.sum("rows").alias("rows"))


@entry("SELECT c_mktsegment, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def bucketed_join(s, d):
    tag = uuid.uuid4().hex[:12]
    a = io.save_bucketed(table(s, d, "orders", ["o_custkey"]), f"orders_{tag}", 8, "o_custkey")
    b = io.save_bucketed(table(s, d, "customer", ["c_custkey", "c_mktsegment"]), f"customer_{tag}", 8, "c_custkey")
    return a.join(b, a.o_custkey == b.c_custkey).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("orders"))


# Projections, filters, predicates


@entry("SELECT o_orderkey AS id, CASE WHEN o_totalprice >= 300000 THEN 'high' WHEN o_totalprice >= 100000 THEN 'mid' ELSE 'low' END AS band, cast(o_totalprice AS bigint) // 1000 AS thousands FROM (SELECT o_orderkey, floor(o_totalprice) AS o_totalprice FROM orders)")
def project_case(s, d):
    o = table(s, d, "orders", ["o_orderkey", "o_totalprice"]).withColumn("o_totalprice", F.floor("o_totalprice"))
    band = F.when(F.col("o_totalprice") >= 300000, "high").when(F.col("o_totalprice") >= 100000, "mid").otherwise("low")
    return o.select(F.col("o_orderkey").alias("id"), band.alias("band"), F.expr("o_totalprice div 1000").alias("thousands"))


@entry("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_shipdate BETWEEN TIMESTAMP '1996-01-01' AND TIMESTAMP '1996-06-30' AND l_returnflag IN ('R', 'N') AND NOT l_quantity < 10")
def filter_range_shipdate(s, d):
    return table(s, d, "lineitem").where("l_shipdate BETWEEN TIMESTAMP_NTZ '1996-01-01' AND TIMESTAMP_NTZ '1996-06-30' AND l_returnflag IN ('R', 'N') AND NOT l_quantity < 10").select("l_orderkey", "l_linenumber", "l_quantity")


@entry("SELECT doc_id FROM documents WHERE text LIKE '%license%' OR text LIKE 'The %' OR regexp_matches(text, '[0-9]{9}')")
def filter_like_text(s, d):
    t = F.col("text")
    return table(s, d, "documents", ["doc_id", "text"]).where(t.contains("license") | t.startswith("The ") | t.rlike("[0-9]{9}")).select("doc_id")


@entry("SELECT l_orderkey, l_linenumber, coalesce(nullif(l_linenumber, 3), -1) AS line FROM lineitem WHERE nullif(l_linenumber, 3) IS NULL OR l_linenumber IS NOT DISTINCT FROM 1")
def filter_nulls(s, d):
    line = F.expr("nullif(l_linenumber, 3)")
    return table(s, d, "lineitem", ["l_orderkey", "l_linenumber"]).where(line.isNull() | F.col("l_linenumber").eqNullSafe(1)).select("l_orderkey", "l_linenumber", F.coalesce(line, F.lit(-1)).alias("line"))


@entry("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 450000)")
def filter_exists(s, d):
    table(s, d, "customer").createOrReplaceTempView("v_customer")
    table(s, d, "orders").createOrReplaceTempView("v_orders")
    return s.sql("SELECT c_custkey FROM v_customer WHERE EXISTS (SELECT 1 FROM v_orders WHERE o_custkey = c_custkey AND o_totalprice > 450000)")


@entry("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT max(o_totalprice) * 0.99 FROM orders)")
def scalar_subquery(s, d):
    table(s, d, "orders").createOrReplaceTempView("v_orders")
    return s.sql("SELECT o_orderkey FROM v_orders WHERE o_totalprice > (SELECT max(o_totalprice) * 0.99D FROM v_orders)")


@entry("SELECT DISTINCT text FROM documents")
def distinct_text(s, d):
    return table(s, d, "documents", ["text"]).distinct()


@entry(f"SELECT o_orderkey FROM orders ORDER BY {DUCK.hash('o_orderkey', 9)}, o_orderkey LIMIT 100")
def sample_bottom(s, d):
    return aggregates.bottom_sample(table(s, d, "orders", ["o_orderkey"]), uid_hash("o_orderkey", 9), 100, "o_orderkey")


@entry(f"SELECT o_orderkey FROM orders WHERE {DUCK.hash('o_orderkey', 9)} < 214748364")
def sample_fraction(s, d):
    return table(s, d, "orders", ["o_orderkey"]).where(uid_hash("o_orderkey", 9) < 214748364)


# Joins

ORDERS_CUSTOMER = "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey"


@entry(ORDERS_CUSTOMER)
def join_shuffle_hash(s, d):
    o, c = table(s, d, "orders"), table(s, d, "customer")
    return o.join(c.hint("shuffle_hash"), o.o_custkey == c.c_custkey).select("o_orderkey", "c_name")


@entry("SELECT l_orderkey, l_linenumber, o_orderpriority FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def join_sort_merge(s, d):
    l, o = table(s, d, "lineitem"), table(s, d, "orders")
    return l.join(o.hint("merge"), l.l_orderkey == o.o_orderkey).select("l_orderkey", "l_linenumber", "o_orderpriority")


@entry("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(s, d):
    n, r = table(s, d, "nation"), table(s, d, "region")
    return n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select("n_name", "r_name")


@entry("SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_retailprice < b.p_retailprice AND b.p_retailprice < a.p_retailprice + 0.15")
def join_theta_price(s, d):
    return joins.theta_band(table(s, d, "part", ["p_partkey", "p_retailprice"]), "p_retailprice", "p_partkey", 0.15)


@entry("SELECT n_name, r_name FROM nation, region")
def join_cross(s, d):
    return table(s, d, "nation", ["n_name"]).crossJoin(table(s, d, "region", ["r_name"]))


@entry("SELECT e.event_id, b.band FROM events e JOIN (SELECT i AS band, i * 20.0 AS low, i * 20.0 + 30.0 AS high FROM (SELECT unnest([0,1,2,3,4,5,6,7,8,9,10,11,12,13,14,15,16,17,18,19,20,21,22,23,24]) AS i)) b ON e.value >= b.low AND e.value < b.high")
def join_range_bands(s, d):
    bands = s.range(25).select(F.col("id").cast("int").alias("band"), (F.col("id") * 20.0).alias("low"), (F.col("id") * 20.0 + 30.0).alias("high"))
    return joins.range_join(table(s, d, "events", ["event_id", "value"]), "value", bands, "low", "high", 10.0).select("event_id", "band")


@entry("""SELECT p.event_id, (SELECT max(v.event_id) FROM events v WHERE v.event_type = 'view' AND v.user_id = p.user_id AND v.ts < p.ts) AS last_view FROM events p WHERE p.event_type = 'purchase'""")
def join_asof(s, d):
    e = table(s, d, "events", ["event_id", "ts", "user_id", "event_type"])
    buys, views = e.where("event_type = 'purchase'").select("event_id", "ts", "user_id"), e.where("event_type = 'view'").select("event_id", "ts", "user_id")
    return joins.asof(buys, views, "ts", ["user_id"], "event_id", "last_view").select("event_id", "last_view")


@entry("SELECT cast(i AS int) AS pe, coalesce(c, 0) AS cnt FROM (SELECT unnest([0,1,2,3,4,5,6,7,8,9]) AS i) LEFT JOIN (SELECT n_regionkey, count(*) AS c FROM nation GROUP BY 1) ON i = n_regionkey")
def join_left_counts(s, d):
    return joins.with_counts(10, table(s, d, "nation").groupBy(F.col("n_regionkey").alias("pe")).agg(F.count(F.lit(1)).alias("cnt"))).na.fill(0)


@entry("SELECT s_suppkey, c_custkey FROM supplier FULL JOIN customer ON s_suppkey = c_custkey AND s_nationkey = c_nationkey")
def join_full(s, d):
    a, b = table(s, d, "supplier"), table(s, d, "customer")
    return a.join(b, (a.s_suppkey == b.c_custkey) & (a.s_nationkey == b.c_nationkey), "full").select("s_suppkey", "c_custkey")


@entry("SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)")
def join_semi(s, d):
    return table(s, d, "orders", ["o_orderkey"]).join(table(s, d, "lineitem").where("l_quantity > 45").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_semi")


@entry("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_anti(s, d):
    return table(s, d, "orders", ["o_orderkey"]).join(table(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_anti")


@entry("""SELECT r_name, count(*) AS lines, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
    JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1""")
def join_star(s, d):
    l, o, c, n, r = (table(s, d, t) for t in ("lineitem", "orders", "customer", "nation", "region"))
    j = l.join(o, l.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return j.groupBy("r_name").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@entry("SELECT c_custkey, max(o_totalprice) AS dearest FROM customer JOIN orders ON o_custkey = c_custkey GROUP BY 1")
def join_lateral_top(s, d):
    table(s, d, "customer").createOrReplaceTempView("v_customer")
    table(s, d, "orders").createOrReplaceTempView("v_orders")
    return s.sql("SELECT c_custkey, dearest FROM v_customer, LATERAL (SELECT max(o_totalprice) AS dearest FROM v_orders WHERE o_custkey = c_custkey) WHERE dearest IS NOT NULL")


@entry("SELECT n_name, count(*) AS lines FROM (SELECT CASE WHEN l_orderkey % 3 = 0 THEN 0 ELSE l_suppkey % 25 END AS k FROM lineitem) JOIN nation ON k = n_nationkey GROUP BY 1")
def join_salted(s, d):
    hot = table(s, d, "lineitem").select(F.expr("cast(CASE WHEN l_orderkey % 3 = 0 THEN 0 ELSE l_suppkey % 25 END AS int) AS k"), "l_orderkey", "l_linenumber")
    n = table(s, d, "nation").select(F.col("n_nationkey").alias("k"), "n_name")
    return joins.salted(hot, n, "k", 8, uid_hash("l_orderkey * 8 + l_linenumber", 3)).groupBy("n_name").agg(F.count(F.lit(1)).alias("lines"))


# Aggregations


@entry("SELECT cast(o_orderkey % 16 AS int) AS pe, count(*) AS cnt, max(o_totalprice) AS top FROM orders GROUP BY 1")
def agg_pe_counts(s, d):
    return table(s, d, "orders").groupBy(F.expr("cast(o_orderkey % 16 AS int)").alias("pe")).agg(F.count(F.lit(1)).alias("cnt"), F.max("o_totalprice").alias("top"))


@entry("SELECT p_brand, string_agg(p_name, ',' ORDER BY p_name, p_partkey) AS names FROM part WHERE p_size < 10 GROUP BY 1")
def agg_collect_sorted(s, d):
    return table(s, d, "part").where("p_size < 10").groupBy("p_brand").agg(F.array_join(F.array_sort(F.collect_list("p_name")), ",").alias("names"))


@entry("SELECT text, count(*) AS run_length FROM documents GROUP BY text")
def app_runs_of_equal(s, d):
    return aggregates.runs_of_equal(table(s, d, "documents", ["text"]), "text")


@entry("SELECT count(*) AS n, round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS dev, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem")
def agg_global(s, d):
    return table(s, d, "lineitem").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("l_quantity"), 6).alias("mean"), F.round(F.stddev_samp("l_quantity"), 6).alias("dev"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"))


@entry("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@entry("SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")
def agg_grouping_sets(s, d):
    table(s, d, "lineitem").createOrReplaceTempView("v_lineitem")
    return s.sql("SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM v_lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")


@entry("SELECT event_type, user_id % 3 AS third, count(*) AS cnt FROM events GROUP BY CUBE (event_type, user_id % 3)")
def agg_cube_events(s, d):
    return table(s, d, "events").withColumn("third", F.col("user_id") % 3).cube("event_type", "third").agg(F.count(F.lit(1)).alias("cnt"))


@entry("SELECT l_returnflag, l_linestatus, cast(sum(l_linenumber) AS bigint) AS total FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def agg_rollup_lineitem(s, d):
    return table(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.sum("l_linenumber").alias("total"))


@entry("SELECT o_orderpriority, quantile_disc(o_totalprice, 0.5) AS q50, quantile_disc(o_totalprice, 0.9) AS q90 FROM orders GROUP BY 1")
def agg_percentiles(s, d):
    table(s, d, "orders").createOrReplaceTempView("v_orders")
    return s.sql("SELECT o_orderpriority, percentile_disc(0.5) WITHIN GROUP (ORDER BY o_totalprice) AS q50, percentile_disc(0.9) WITHIN GROUP (ORDER BY o_totalprice) AS q90 FROM v_orders GROUP BY 1")


@entry("SELECT user_id % 5 AS k, max(c) AS times FROM (SELECT user_id % 5 AS user_id, event_type, count(*) AS c FROM events GROUP BY ALL) GROUP BY 1")
def agg_mode(s, d):
    e = table(s, d, "events").select((F.col("user_id") % 5).alias("k"), "event_type")
    top = e.groupBy("k").agg(F.mode("event_type").alias("event_type"))
    return e.join(top, ["k", "event_type"]).groupBy("k").agg(F.count(F.lit(1)).alias("times"))


@entry("SELECT round(regr_slope(ln(l_extendedprice), ln(l_quantity)), 6) AS slope, round(regr_intercept(ln(l_extendedprice), ln(l_quantity)), 6) AS intercept FROM lineitem")
def agg_regr(s, d):
    return table(s, d, "lineitem").select(F.ln("l_extendedprice").alias("y"), F.ln("l_quantity").alias("x")).agg(F.round(F.regr_slope("y", "x"), 6).alias("slope"), F.round(F.regr_intercept("y", "x"), 6).alias("intercept"))


@entry("SELECT l_returnflag, max(l_extendedprice) AS price FROM lineitem GROUP BY 1")
def agg_max_by(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.max_by("l_extendedprice", "l_extendedprice").alias("price"))


@entry("SELECT l_returnflag, count(*) FILTER (WHERE l_quantity > 25) AS large, count(*) AS n FROM lineitem GROUP BY 1")
def agg_filter(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_if(F.col("l_quantity") > 25).alias("large"), F.count(F.lit(1)).alias("n"))


@entry("SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'F') AS f, count(*) FILTER (WHERE l_linestatus = 'O') AS o FROM lineitem GROUP BY 1")
def agg_pivot(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@entry("SELECT r_regionkey, 'a' AS name, cast(r_regionkey AS bigint) AS v FROM region UNION ALL SELECT r_regionkey, 'b', cast(length(r_name) AS bigint) FROM region")
def agg_unpivot(s, d):
    wide = table(s, d, "region").select("r_regionkey", F.col("r_regionkey").cast("long").alias("a"), F.length("r_name").cast("long").alias("b"))
    return wide.unpivot("r_regionkey", ["a", "b"], "name", "v")


@entry("SELECT cast(floor((l_quantity - 1) / 7) AS bigint) + 1 AS bucket, count(*) AS cnt FROM lineitem GROUP BY 1")
def agg_histogram(s, d):
    return table(s, d, "lineitem").groupBy(F.expr("width_bucket(l_quantity, 1, 57, 8)").alias("bucket")).agg(F.count(F.lit(1)).alias("cnt"))


@entry("SELECT cast(l_quantity > 10 AS int) + cast(l_quantity > 20 AS int) + cast(l_quantity > 40 AS int) AS bucket, count(*) AS cnt FROM lineitem GROUP BY 1")
def agg_bucket_counts(s, d):
    return aggregates.bucket_counts(table(s, d, "lineitem"), "l_quantity", [10.0, 20.0, 40.0])


# Windows, sorts, limits, set operations

def _per_user():
    return Window.partitionBy("user_id").orderBy("ts")


@entry("""SELECT event_id, row_number() OVER w AS rn, rank() OVER v AS r, dense_rank() OVER v AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd
    FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts), v AS (PARTITION BY user_id ORDER BY event_type)""")
def win_rank_family(s, d):
    v = Window.partitionBy("user_id").orderBy("event_type")
    return table(s, d, "events").select("event_id", F.row_number().over(_per_user()).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("r"), F.dense_rank().over(v).cast("long").alias("dr"), F.ntile(4).over(_per_user()).cast("long").alias("quarter"), F.round(F.percent_rank().over(_per_user()), 9).alias("pr"), F.round(F.cume_dist().over(_per_user()), 9).alias("cd"))


@entry("""SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after, first_value(event_id) OVER w AS first, last_value(event_id) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last, nth_value(event_id, 2) OVER w AS second
    FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)""")
def win_lag_lead(s, d):
    full = _per_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    e = F.col("event_id")
    return table(s, d, "events").select("event_id", F.lag(e).over(_per_user()).alias("before"), F.lead(e, 2).over(_per_user()).alias("after"), F.first(e).over(_per_user()).alias("first"), F.last(e).over(full).alias("last"), F.nth_value(e, 2).over(_per_user()).alias("second"))


@entry("SELECT pe, cast(coalesce(sum(c) OVER (ORDER BY pe ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS bigint) AS before FROM (SELECT cast(o_orderkey % 16 AS int) AS pe, count(*) AS c FROM orders GROUP BY 1)")
def win_prefix_sum(s, d):
    counts = agg_pe_counts(s, d)
    return counts.select("pe", F.coalesce(F.sum("cnt").over(Window.orderBy("pe").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))


@entry("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean FROM events")
def win_sliding_avg(s, d):
    return table(s, d, "events").select("event_id", F.round(F.avg("value").over(_per_user().rowsBetween(-2, 0)), 6).alias("mean"))


@entry("""SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS near, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS hour FROM events""")
def win_range_frame(s, d):
    table(s, d, "events").createOrReplaceTempView("v_events")
    return s.sql("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS near, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS hour FROM v_events")


@entry("SELECT row_number() OVER (ORDER BY l_shipdate DESC, l_quantity, l_orderkey, l_linenumber, l_partkey, l_suppkey) - 1 AS rank, l_shipdate, l_quantity, l_orderkey FROM lineitem")
def sort_global_multi(s, d):
    from .functions.keys import By

    l = table(s, d, "lineitem", ["l_shipdate", "l_quantity", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"])
    return global_rank(l, [By("l_shipdate", False), "l_quantity", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]).select("rank", "l_shipdate", "l_quantity", "l_orderkey")


@entry("SELECT pe, row_number() OVER (PARTITION BY pe ORDER BY o_totalprice, o_orderkey) AS place, o_orderkey FROM (SELECT cast(o_orderkey % 16 AS int) AS pe, o_totalprice, o_orderkey FROM orders)")
def sort_within_pe(s, d):
    o = table(s, d, "orders", ["o_orderkey", "o_totalprice"]).withColumn("pe", F.expr("cast(o_orderkey % 16 AS int)"))
    o = o.repartitionById(16, F.col("pe")).sortWithinPartitions("o_totalprice", "o_orderkey")
    return o.select("pe", F.row_number().over(Window.partitionBy("pe").orderBy("o_totalprice", "o_orderkey")).cast("long").alias("place"), "o_orderkey")


@entry("SELECT o_orderkey FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 50 OFFSET 20")
def limit_offset(s, d):
    return table(s, d, "orders", ["o_orderkey", "o_totalprice"]).orderBy("o_totalprice", "o_orderkey").offset(20).limit(50).select("o_orderkey")


@entry("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")
def topk_orders(s, d):
    return table(s, d, "orders", ["o_orderkey", "o_totalprice"]).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100)


@entry("SELECT l_orderkey, place, l_extendedprice FROM (SELECT l_orderkey, l_extendedprice, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_extendedprice DESC) AS place FROM lineitem) WHERE place <= 3")
def topk_per_group(s, d):
    place = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(F.desc("l_extendedprice"))).cast("long")
    return table(s, d, "lineitem").withColumn("place", place).where("place <= 3").select("l_orderkey", "place", "l_extendedprice")


@entry("SELECT o_totalprice AS key FROM orders ORDER BY o_totalprice LIMIT 1 OFFSET 700")
def kth_smallest(s, d):
    return global_rank(table(s, d, "orders", ["o_totalprice"]), "o_totalprice").where("rank = 700").select(F.col("o_totalprice").alias("key"))


@entry("SELECT cast(r * 7 // n AS int) AS part, count(*) AS cnt, min(o_totalprice) AS low, max(o_totalprice) AS high FROM (SELECT o_totalprice, row_number() OVER (ORDER BY o_totalprice) - 1 AS r, count(*) OVER () AS n FROM orders) GROUP BY 1")
def equal_weight_cuts(s, d):
    ranked = global_rank(table(s, d, "orders", ["o_totalprice"]), "o_totalprice").withColumnRenamed("o_totalprice", "key")
    return aggregates.equal_weight_cuts(ranked, 7, ranked.count())


@entry("SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier UNION ALL SELECT n_nationkey FROM nation")
def set_union(s, d):
    a, b, c = table(s, d, "customer").select(F.col("c_nationkey").alias("k")), table(s, d, "supplier").select(F.col("s_nationkey").alias("k")), table(s, d, "nation").select(F.col("n_nationkey").alias("k"))
    return a.union(b).distinct().unionByName(c)


@entry("SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def set_intersect_all(s, d):
    return table(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(table(s, d, "supplier").select(F.col("s_nationkey").alias("k")))


@entry("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def set_except_all(s, d):
    return table(s, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(table(s, d, "supplier").select(F.col("s_nationkey").alias("k")))


# Scalar functions


@entry("SELECT page_id, lower(substring(url, 1, 8)) AS head, length(url) AS n, reverse(lpad(cast(page_id AS varchar), 6, '0')) AS back, regexp_extract(url, '://([^/]+)', 1) AS host, levenshtein(substring(url, 1, 12), 'https://www.') AS edits FROM pages")
def fn_string(s, d):
    u = F.col("url")
    return table(s, d, "pages", ["page_id", "url"]).select("page_id", F.lower(F.substring(u, 1, 8)).alias("head"), F.length(u).cast("long").alias("n"), F.reverse(F.lpad(F.col("page_id").cast("string"), 6, "0")).alias("back"), F.regexp_extract(u, "://([^/]+)", 1).alias("host"), F.levenshtein(F.substring(u, 1, 12), F.lit("https://www.")).cast("long").alias("edits"))


@entry("SELECT o_orderkey, date_trunc('month', o_orderdate) AS month, date_diff('day', DATE '1992-01-01', cast(o_orderdate AS date)) AS days, year(o_orderdate) AS y, o_orderdate + INTERVAL 3 DAY AS later FROM orders")
def fn_date(s, d):
    o = F.col("o_orderdate")
    return table(s, d, "orders", ["o_orderkey", "o_orderdate"]).select("o_orderkey", F.date_trunc("month", o).cast("timestamp_ntz").alias("month"), F.date_diff(o.cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"), F.year(o).cast("long").alias("y"), (o + F.expr("INTERVAL 3 DAY")).alias("later"))


@entry("SELECT l_orderkey, l_linenumber, cast(floor(l_quantity / 7) AS bigint) AS f, greatest(l_quantity, l_tax * 100) AS g, round(log2(l_quantity), 9) AS lg, round(sqrt(l_extendedprice), 9) AS root, round(pow(l_discount, 2), 9) AS sq, abs(l_linenumber - 4) AS a FROM lineitem")
def fn_math(s, d):
    q = F.col("l_quantity")
    return table(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.floor(q / 7).alias("f"), F.greatest(q, F.col("l_tax") * 100).alias("g"), F.round(F.log2(q), 9).alias("lg"), F.round(F.sqrt("l_extendedprice"), 9).alias("root"), F.round(F.pow("l_discount", F.lit(2)), 9).alias("sq"), F.abs(F.col("l_linenumber") - 4).alias("a"))


@entry("SELECT o_orderkey, o_orderkey >> 2 AS r, o_orderkey << 3 AS l, xor(o_orderkey, 21) AS x, o_orderkey & 12 AS a, o_orderkey | 5 AS o, cast(bit_count(o_orderkey) AS bigint) AS n FROM orders")
def fn_bits(s, d):
    k = F.col("o_orderkey")
    return table(s, d, "orders", ["o_orderkey"]).select("o_orderkey", F.shiftright(k, 2).alias("r"), F.shiftleft(k, 3).alias("l"), k.bitwiseXOR(F.lit(21)).alias("x"), k.bitwiseAND(F.lit(12)).alias("a"), k.bitwiseOR(F.lit(5)).alias("o"), F.bit_count(k).cast("long").alias("n"))


@entry("SELECT vec_id, cast(len(embedding) AS bigint) AS n, round(cast(list_min(embedding) AS double), 6) AS low, round(cast(embedding[3] AS double), 6) AS third, cast(len(list_filter(embedding, lambda x: x > 0)) AS bigint) AS positive FROM embeddings")
def fn_array(s, d):
    e = F.col("embedding")
    return table(s, d, "embeddings", ["vec_id", "embedding"]).select("vec_id", F.size(e).cast("long").alias("n"), F.round(F.get(F.array_sort(e), F.lit(0)).cast("double"), 6).alias("low"), F.round(F.element_at(e, 3).cast("double"), 6).alias("third"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"))


@entry("SELECT user_id, event_type AS k, 2 * count(*) AS v FROM events GROUP BY 1, 2")
def fn_map(s, d):
    counts = table(s, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("c"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "c"))).alias("m"))
    return maps.select("user_id", F.explode(F.transform_values("m", lambda k, v: v * 2)).alias("k", "v"))


@entry("SELECT user_id, event_id FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY event_type DESC, value DESC, event_id DESC) AS r FROM events) WHERE r = 1")
def fn_struct_order(s, d):
    return table(s, d, "events").groupBy("user_id").agg(F.max(F.struct("event_type", "value", "event_id")).alias("m")).select("user_id", F.col("m.event_id").alias("event_id"))


@entry("SELECT event_id, cast(json_extract_string(props, '$.k') AS bigint) AS k FROM events")
def fn_json(s, d):
    return table(s, d, "events", ["event_id", "props"]).select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@entry(f"SELECT o_orderkey, {DUCK.hash('o_orderkey', 5)} AS h, md5(cast(o_orderkey AS varchar)) AS m FROM orders")
def fn_hash(s, d):
    return table(s, d, "orders", ["o_orderkey"]).select("o_orderkey", uid_hash("o_orderkey", 5).alias("h"), F.md5(F.col("o_orderkey").cast("string")).alias("m"))


@entry("SELECT l_orderkey, l_linenumber, coalesce(nullif(l_tax, 0.0), -1.0) AS tax, CASE WHEN l_discount > 0.05 THEN 'much' END AS flag FROM lineitem")
def fn_nulls(s, d):
    return table(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.coalesce(F.nullif("l_tax", F.lit(0.0)), F.lit(-1.0)).alias("tax"), F.when(F.col("l_discount") > 0.05, "much").alias("flag"))


@entry(f"SELECT l_orderkey, l_linenumber, {morton_sql('l_partkey', 'l_suppkey', True)} AS code FROM lineitem")
def fn_morton(s, d):
    return table(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.expr(morton_sql("l_partkey", "l_suppkey")).alias("code"))


# Applications


@entry(f"""SELECT cast(r * 16 // n AS int) AS part, count(*) AS cnt, min(code) AS low, max(code) AS high FROM (SELECT code, row_number() OVER (ORDER BY code) - 1 AS r, count(*) OVER () AS n
    FROM (SELECT {morton_sql('l_partkey', 'l_suppkey', True)} AS code FROM lineitem)) GROUP BY 1""")
def app_space_curve(s, d):
    coded = table(s, d, "lineitem").select(F.expr(morton_sql("l_partkey", "l_suppkey")).alias("key"))
    ranked = global_rank(coded, "key")
    return aggregates.equal_weight_cuts(ranked, 16, ranked.count())


@entry("SELECT c_custkey, c_nationkey AS colour, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey) - 1 AS place FROM customer")
def app_group_split(s, d):
    """Each input's rank inside its colour: a global rank in (colour, key) less the colour's first."""
    ranked = global_rank(table(s, d, "customer", ["c_custkey", "c_nationkey"]), ["c_nationkey", "c_custkey"])
    first = ranked.groupBy("c_nationkey").agg(F.min("rank").alias("first"))
    return ranked.join(first, "c_nationkey").select("c_custkey", F.col("c_nationkey").alias("colour"), (F.col("rank") - F.col("first")).alias("place"))


# Streaming: events replayed as files; the oracle is the batch form


#: Replayed files come in the order of time, so no row is later than this.
LATE = "1 hour"


def _events(s, d, parts=4) -> DataFrame:
    rows = table(s, d, "events")
    return stream.stamped(stream.files(s, stream.replay(s, rows, parts, "ts"), rows.schema))


def _name() -> str:
    return f"s_{uuid.uuid4().hex}"


def _ntz(c: str, alias: str):
    return F.col(c).cast("timestamp_ntz").alias(alias)


@entry("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS cnt FROM events GROUP BY 1, 2")
def stream_tumbling(s, d):
    out = stream.run(stream.tumbling(stream.with_lateness(_events(s, d), "1 hour"), "1 hour", F.count(F.lit(1)).alias("cnt"), keys=("event_type",)), _name(), "complete")
    return out.select(_ntz("w.start", "start"), "event_type", "cnt")


@entry("SELECT start, count(*) AS cnt FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - i * INTERVAL 30 MINUTE AS start, ts FROM events, (SELECT unnest([0, 1]) AS i)) GROUP BY 1")
def stream_sliding(s, d):
    out = stream.run(stream.sliding(stream.with_lateness(_events(s, d), "1 hour"), "1 hour", "30 minutes", F.count(F.lit(1)).alias("cnt")), _name(), "complete")
    return out.select(_ntz("w.start", "start"), "cnt")


@entry("""SELECT user_id, min(ts) AS start, count(*) AS cnt FROM (SELECT user_id, ts, sum(brk) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM (SELECT user_id, ts,
    CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS brk FROM events)) GROUP BY user_id, g""")
def stream_session(s, d):
    out = stream.run(stream.session(stream.with_lateness(_events(s, d), LATE), "2 hours", F.count(F.lit(1)).alias("cnt"), keys=("user_id",)), _name(), "complete")
    return out.select("user_id", _ntz("w.start", "start"), "cnt")


@entry("SELECT event_id, user_id, event_type FROM events")
def stream_dedup(s, d):
    """Every event comes twice; keys are forgotten once the watermark has passed them."""
    rows = table(s, d, "events").withColumn("_copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("_copy")
    twice = stream.stamped(stream.files(s, stream.replay(s, rows, 4, "ts"), rows.schema))
    return stream.run(stream.dedup(stream.with_lateness(twice, LATE), "event_id").select("event_id", "user_id", "event_type"), _name())


@entry("""WITH r AS (SELECT ts, (row_number() OVER (ORDER BY event_id % 10 = 3, event_id) - 1) * 4 // count(*) OVER () AS b FROM events), w AS (SELECT b, max(ts) AS latest FROM r GROUP BY b)
    SELECT late, count(*) AS cnt FROM (SELECT coalesce(ts < (SELECT max(latest) FROM w WHERE w.b < r.b) - INTERVAL 1 HOUR, false) AS late FROM r) GROUP BY late""")
def stream_late_rows(s, d):
    """A tenth of the events comes after all others."""
    rows = table(s, d, "events").withColumn("behind", F.expr("event_id % 10 = 3"))
    source = stream.stamped(stream.files(s, stream.replay(s, rows, 4, ["behind", "event_id"]), rows.schema))
    return stream.with_late_rows(source, "1 hour", _name()).groupBy("late").agg(F.count(F.lit(1)).alias("cnt"))


@entry("SELECT event_id, c_mktsegment FROM events LEFT JOIN customer ON user_id = c_custkey")
def stream_join_static(s, d):
    c = table(s, d, "customer", ["c_custkey", "c_mktsegment"])
    rows = _events(s, d)
    return stream.run(stream.enrich(rows, c, rows.user_id == c.c_custkey).select("event_id", "c_mktsegment"), _name())


@entry("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def stream_join_interval(s, d):
    views = stream.with_lateness(_events(s, d).where("event_type = 'view'"), LATE)
    buys = stream.with_lateness(_events(s, d).where("event_type = 'purchase'"), LATE)
    return stream.run(stream.pair(views, buys, "user_id", "0 seconds", "30 minutes").select(F.col("a_event_id").alias("a"), F.col("b_event_id").alias("b")), _name())


@entry("SELECT event_type AS key, cast(place AS int) AS place, value FROM (SELECT event_type, value, row_number() OVER (PARTITION BY event_type ORDER BY value DESC) AS place FROM events) WHERE place <= 3")
def stream_topk_state(s, d):
    rows = table(s, d, "events", ["event_id", "event_type", "value"])
    source = stream.files(s, stream.replay(s, rows, 2, "event_id"), rows.schema)
    s.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return stream.run(stream.topk_state(source, "event_type", "value", 3), _name(), "update", keys=("key",))
    finally:
        s.conf.unset("spark.sql.streaming.stateStore.providerClass")


@entry("SELECT b AS batch, row_number() OVER (PARTITION BY b ORDER BY value) - 1 AS rank, value FROM (SELECT value, cast((row_number() OVER (ORDER BY event_id) - 1) * 4 // count(*) OVER () AS int) AS b FROM events)")
def stream_batch_sort(s, d):
    path = _path(s)
    rows = table(s, d, "events", ["event_id", "value"])
    source = stream.files(s, stream.replay(s, rows, 4, "event_id"), rows.schema)
    q = stream.sort_batches(source, "value", path).trigger(availableNow=True).option("checkpointLocation", _path(s)).start()
    q.awaitTermination()
    return s.read.parquet(path).select("batch", "rank", "value")


@entry("""SELECT pe, uid, row_number() OVER (PARTITION BY pe ORDER BY key, uid) AS pos, count(*) OVER (PARTITION BY pe) AS m, count(*) FILTER (WHERE key < 25) OVER (PARTITION BY pe) AS lt, count(*) FILTER (WHERE key = 25) OVER (PARTITION BY pe) AS eq
    FROM (SELECT cast(uid * 16 // n AS int) AS pe, l_quantity AS key, uid FROM (SELECT l_quantity, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate) - 1 AS uid, count(*) OVER () AS n FROM lineitem))""")
def win_local_split(s, d):
    """Places of elements on their PE with the counts of smaller and equal ones, in one pass over a window."""
    ids = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"]
    ranked = global_rank(table(s, d, "lineitem", [*ids, "l_quantity"]), ids, "uid")
    n = ranked.count()
    per = Window.partitionBy("pe")
    held = ranked.select(F.expr(f"cast(uid * 16 div {max(n, 1)} AS int)").alias("pe"), F.col("l_quantity").alias("key"), "uid")
    counts = [F.sum(test.cast("long")).over(per).alias(name) for name, test in (("lt", F.col("key") < 25), ("eq", F.col("key") == 25))]
    return held.select("pe", "uid", F.row_number().over(per.orderBy("key", "uid")).alias("pos"), F.count(F.lit(1)).over(per).alias("m"), *counts)


@entry("SELECT event_type, true AS near FROM events GROUP BY event_type")
def agg_approx_distinct(s, d):
    """Whether the sketched number of users is within four standard errors of the exact one."""
    per = table(s, d, "events", ["event_type", "user_id"]).groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("sketched"), F.countDistinct("user_id").alias("exact"))
    return per.select("event_type", (F.abs(F.col("sketched") / F.col("exact") - 1) <= 0.08).alias("near"))


@entry("SELECT o_orderstatus, true AS near FROM orders GROUP BY o_orderstatus")
def agg_sketched_pivots(s, d):
    """Whether a quantile sketch's median would do as a pivot: its relative rank error is within the sketch's bound."""
    rows = table(s, d, "orders", ["o_orderstatus", "o_totalprice"])
    pivots = rows.groupBy("o_orderstatus").agg(F.percentile_approx("o_totalprice", 0.5, 1000).alias("s"))
    ranks = rows.join(F.broadcast(pivots), "o_orderstatus").groupBy("o_orderstatus").agg(F.sum((F.col("o_totalprice") <= F.col("s")).cast("long")).alias("rank"), F.count(F.lit(1)).alias("n"))
    return ranks.select("o_orderstatus", (medians.rank_error(F.col("rank"), F.col("n")) <= 0.01).alias("near"))


# Python functions and table functions


@entry("SELECT l_orderkey, l_linenumber, cast(l_quantity > 10 AS int) + cast(l_quantity > 20 AS int) + cast(l_quantity > 40 AS int) AS bucket FROM lineitem")
def udf_searchsorted(s, d):
    return table(s, d, "lineitem").select("l_orderkey", "l_linenumber", udfs.searchsorted([10.0, 20.0, 40.0])("l_quantity").alias("bucket"))


@entry("SELECT cast(o_orderkey % 4 AS int) AS pe, row_number() OVER (PARTITION BY o_orderkey % 4 ORDER BY o_totalprice) AS pos, o_totalprice AS key FROM orders")
def udf_merge_runs(s, d):
    runs = table(s, d, "orders").select(F.expr("cast(o_orderkey % 4 AS int) AS pe"), F.expr("o_orderkey % 3 AS run"), F.col("o_totalprice").alias("key"))
    return udfs.merge_runs(runs, "pe", "run", "key")


@entry("SELECT cast(l_quantity > 10 AS int) + cast(l_quantity > 20 AS int) + cast(l_quantity > 40 AS int) AS bucket, count(*) AS cnt FROM lineitem GROUP BY 1")
def udf_classify_batches(s, d):
    return udfs.classify_batches(table(s, d, "lineitem"), "l_quantity", [10.0, 20.0, 40.0])


@entry("SELECT o_orderpriority, quantile_disc(o_totalprice, 0.5) AS low FROM orders GROUP BY 1")
def udaf_median_window(s, d):
    return table(s, d, "orders").groupBy("o_orderpriority").agg(udfs.median_window("o_totalprice").alias("w")).select("o_orderpriority", F.col("w")[0].alias("low"))


@entry("SELECT cast(k AS int) AS round, cast(pe AS int) AS pe, cast(xor(pe, 1 << (2 - k)) AS int) AS partner FROM (SELECT unnest([0, 1, 2]) AS k), (SELECT unnest([0,1,2,3,4,5,6,7]) AS pe)")
def udtf_cube_schedule(s, d):
    return udfs.CubeSchedule(F.lit(3))


@entry("""WITH h AS (SELECT o_orderkey % 8 AS pe, count(*) AS c FROM orders GROUP BY 1)
    SELECT cast(s AS int) AS phase, cast(j AS int) AS dim, cast(p AS int) AS pe, cast(xor(p, 1 << j) AS int) AS partner, (p >> (s + 1)) & 1 = 0 AS ascending, coalesce(c, 0) AS held
    FROM (SELECT unnest([0, 1, 2]) AS s), (SELECT unnest([0, 1, 2]) AS j), (SELECT unnest([0,1,2,3,4,5,6,7]) AS p) LEFT JOIN h ON h.pe = p WHERE j <= s""")
def udtf_bitonic_schedule(s, d):
    """Who meets whom, with the orders that a PE brings."""
    held = table(s, d, "orders", ["o_orderkey"]).groupBy((F.col("o_orderkey") % 8).cast("int").alias("pe")).agg(F.count(F.lit(1)).alias("held"))
    return udfs.BitonicSchedule(F.lit(3)).join(held, "pe", "left").select("phase", "dim", "pe", "partner", "ascending", F.coalesce("held", F.lit(0)).cast("long").alias("held"))


@entry("SELECT cast(row_number() OVER (PARTITION BY n_regionkey ORDER BY n_name) AS int) AS place, n_name FROM nation")
def udtf_sorted_by(s, d):
    udfs.register(s)
    table(s, d, "nation").createOrReplaceTempView("v_nation")
    return s.sql("SELECT place, n_name FROM sorted_by(TABLE(SELECT n_name, n_regionkey FROM v_nation) PARTITION BY n_regionkey ORDER BY n_name)")


QUERIES = {name: f for name, (f, _) in ENTRIES.items()}
ORACLE = {name: sql for name, (_, sql) in ENTRIES.items() if sql}
