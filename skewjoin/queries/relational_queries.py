"""Surrounding operators and the streaming slice."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.keys import ZipfRows
from ..operators import relational as rel
from ..plans import stats
from ..plans.metrics import imbalance_udaf
from ..sources import catalog
from ..sources.catalog import load
from ..streaming import heavy


def rollup(spark, d):
    return rel.rollup(load(spark, d, "lineitem"), ["l_returnflag", "l_linestatus"], n=F.count(F.lit(1)), q=F.sum(F.col("l_quantity").cast("long")))


def cube(spark, d):
    return rel.cube(load(spark, d, "orders"), ["o_orderstatus", "o_orderpriority"], n=F.count(F.lit(1)))


def grouping_sets(spark, d):
    load(spark, d, "events").createOrReplaceTempView("gs_events")
    return spark.sql("SELECT event_type, coalesce(user_id % 5, -1) AS g, count(*) AS n FROM gs_events GROUP BY GROUPING SETS ((event_type), (user_id % 5), ())")


def topk(spark, d):
    o = load(spark, d, "orders").select("o_orderpriority", "o_orderkey", F.round("o_totalprice", 2).alias("price"))
    return rel.topk(o, ["o_orderpriority"], [F.desc("price"), F.col("o_orderkey")], 3).withColumn("place", F.col("place").cast("long"))


def ranked(spark, d):
    s = load(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    out = rel.ranked(s, ["s_nationkey"], [F.col("s_suppkey")])
    return out.select("s_suppkey", *[F.col(c).cast("long").alias(c) for c in ("rn", "rk", "dr", "qt")])


def running(spark, d):
    e = load(spark, d, "events").select("user_id", "event_id", (F.col("event_id") % 11).alias("v"))
    return rel.running(e, ["user_id"], [F.col("event_id")], "v").fillna(-1, ["prev", "next"])


def asof(spark, d):
    e = load(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    left = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    right = e.where("event_type = 'click'").select("user_id", F.col("ts").alias("click_ts"), F.col("event_id").alias("click_id"))
    return rel.asof(left, right.groupBy("user_id", "click_ts").agg(F.max("click_id").alias("click_id")), "user_id", "ts", "click_ts", "click_id", "last_click").select("event_id", F.coalesce("last_click", F.lit(-1)).alias("last_click"))


def interval(spark, d):
    e = load(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    a = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    b = e.where("event_type = 'click'").select(F.col("event_id").alias("other_id"), "user_id", F.col("ts").alias("other_ts"))
    return rel.interval_join(a, b, "user_id", "ts", "other_ts", 6 * 3600).select("event_id", "other_id")


def range_lookup(spark, d):
    spans = spark.createDataFrame([(i, lo, hi) for i, (lo, hi) in enumerate(((0, 100), (100, 1000), (1000, 10**6)))], "band int, low long, high long")
    p = load(spark, d, "customer").select("c_custkey")
    return rel.range_join(p, spans, "c_custkey", "low", "high", 1000).groupBy(F.col("band").cast("long").alias("band")).agg(F.count(F.lit(1)).alias("n"))


def set_intersect(spark, d):
    r = stats.exact_skew(load(spark, d, "lineitem").select(F.col("l_linenumber").cast("long").alias("k")), "k", 0.1)
    s = stats.exact_skew(load(spark, d, "conversations").select(F.col("turn").alias("k")), "k", 0.1)
    return rel.intersect_keys(r, s)


def set_except(spark, d):
    r = stats.exact_skew(load(spark, d, "lineitem").select(F.col("l_linenumber").cast("long").alias("k")), "k", 0.1)
    s = stats.exact_skew(load(spark, d, "conversations").select(F.col("turn").alias("k")), "k", 0.1)
    return rel.except_keys(r, s)


def set_union_distinct(spark, d):
    return load(spark, d, "nation").select(F.col("n_regionkey").alias("k")).union(load(spark, d, "region").select("r_regionkey")).distinct()


def json_props(spark, d):
    e = load(spark, d, "events").select("event_id", "props")
    keys = F.json_object_keys("props")
    return e.select(F.explode(keys).alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


def strings(spark, d):
    c = load(spark, d, "customer")
    return c.select("c_custkey", F.upper("c_name").alias("up"), F.substring("c_name", 1, 4).alias("head"), F.length("c_name").cast("long").alias("len"),
                    F.regexp_replace("c_name", "[0-9]+", "#").alias("masked"), F.concat_ws("-", "c_mktsegment", F.col("c_nationkey").cast("string")).alias("tag"), F.md5(F.col("c_name").cast("binary")).alias("h"))


def dates(spark, d):
    li = load(spark, d, "lineitem").where((F.col("l_shipdate") >= F.to_timestamp(F.lit("1995-01-01"))) & (F.col("l_shipdate") < F.to_timestamp(F.lit("1997-01-01"))))
    return li.groupBy(F.year("l_shipdate").cast("long").alias("y"), F.quarter("l_shipdate").cast("long").alias("q")).agg(F.count(F.lit(1)).alias("n"), F.max(F.datediff(F.col("l_shipdate"), F.to_date(F.lit("1995-01-01")))).cast("long").alias("last_day"))


def distincts(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.col("user_id") % 10, F.col("event_type")).alias("pairs"))


def filters(spark, d):
    p = load(spark, d, "part")
    return p.where(F.col("p_size").between(5, 15) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13") & ~F.col("p_type").like("%TIN%") & F.col("p_retailprice").isNotNull()).select("p_partkey", F.when(F.col("p_size") > 10, "big").otherwise("small").alias("kind"))


def arrays(spark, d):
    e = load(spark, d, "embeddings").select("vec_id", "label", F.slice("embedding", 1, 3).alias("h"))
    return e.select("vec_id", F.size("h").cast("long").alias("n"), F.size(F.filter("h", lambda x: x > 0)).cast("long").alias("positive"), F.array_contains(F.transform("h", lambda x: x > 0), True).alias("any_positive"))


def maps(spark, d):
    m = F.create_map(*[F.lit(v) for kv in {"click": 1, "view": 2, "purchase": 3}.items() for v in kv])
    e = load(spark, d, "events").select(F.coalesce(F.try_element_at(m, F.col("event_type")), F.lit(0)).cast("long").alias("code"))
    return e.groupBy("code").agg(F.count(F.lit(1)).alias("n"))


def unpivoted(spark, d):
    li = load(spark, d, "lineitem").agg(F.sum("l_linenumber").alias("numbers"), F.count(F.lit(1)).alias("rows"), F.max("l_orderkey").alias("largest"))
    return li.unpivot([], ["numbers", "rows", "largest"], "what", "value")


def pivoted(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1)))


def quantiles(spark, d):
    return load(spark, d, "orders").agg(F.percentile(F.col("o_custkey"), 0.5).alias("median"), F.min("o_custkey").alias("low"), F.max("o_custkey").alias("high"))


def zipf_table(spark, d):
    """Frequencies of the ranks that the Python table function draws for the customers."""
    ZipfRows.register(spark)
    load(spark, d, "customer").select("c_custkey").createOrReplaceTempView("zipf_customers")
    return spark.sql("SELECT rank, count(*) AS n FROM zipf_customers, LATERAL zipf_rows(c_custkey, 1.2D, 20) GROUP BY rank")


def imbalance(spark, d):
    n = load(spark, d, "lineitem").groupBy((F.col("l_orderkey") % 6).alias("node")).agg(F.count(F.lit(1)).cast("double").alias("n"))
    return n.agg(F.round(imbalance_udaf("n"), 6).alias("max_over_mean"))


def bag_equal(spark, d):
    """Two plans of one join compared as bags: no rows."""
    o, c = load(spark, d, "orders").select("o_orderkey", "o_custkey"), load(spark, d, "customer").select("c_custkey", "c_nationkey")
    on = F.col("o_custkey") == F.col("c_custkey")
    return rel.bag_difference(o.join(c.hint("merge"), on), o.join(F.broadcast(c), on)).select("o_orderkey", "side")


def observed_rows(spark, d):
    """Rows that pass a filter, and the sum of a column, measured while they are consumed."""
    rows, seen = catalog.observed(load(spark, d, "lineitem").where("l_quantity > 30"), n=F.count(F.lit(1)), total=F.sum("l_linenumber"))
    catalog.consume(rows)
    return spark.createDataFrame([(seen.get["n"], seen.get["total"])], "n long, total long")


def stream_tumbling(spark, d):
    return heavy.run_available(heavy.windowed_counts(heavy.replay(spark, f"{d}/events.parquet"), "ts", "event_type", "1 day"), "complete").withColumn("start", F.unix_timestamp("start"))


def stream_sliding(spark, d):
    return heavy.run_available(heavy.windowed_counts(heavy.replay(spark, f"{d}/events.parquet"), "ts", "event_type", "2 days", "1 day"), "complete").withColumn("start", F.unix_timestamp("start"))


def stream_session(spark, d):
    return heavy.run_available(heavy.session_counts(heavy.replay(spark, f"{d}/events.parquet"), "ts", "user_id", "1 hour"), "complete").groupBy("key").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n"))


def stream_pairs(spark, d):
    """Stream-stream interval join: a user's next events within ten minutes."""
    e = heavy.replay(spark, f"{d}/events.parquet").select("event_id", "user_id", "ts", "event_type")
    left, right = e.where("event_type = 'view' or event_type = 'click'"), e
    out = heavy.run_available(heavy.interval_pairs(left, right, "user_id", "ts", "10 minutes"))
    return out.select("user_id", "event_id", "right_event_id")


def stream_enrich(spark, d):
    e = heavy.replay(spark, f"{d}/events.parquet").select("event_id", F.col("user_id").alias("a"))
    c = load(spark, d, "customer").select(F.col("c_custkey").alias("b"), "c_mktsegment")
    sink, path = heavy.to_files(spark, "enriched")
    heavy.enrich(e, c, "a", "b", sink, p=0.2, n=4).awaitTermination()
    return spark.read.parquet(path).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


QUERIES = {
    "rollup_flags": rollup, "cube_orders": cube, "grouping_sets_events": grouping_sets, "window_topk_orders": topk, "window_ranked_suppliers": ranked,
    "window_running_events": running, "asof_click": asof, "interval_click": interval, "range_join_bands": range_lookup, "setops_intersect": set_intersect,
    "setops_except": set_except, "setops_union_distinct": set_union_distinct, "json_keys": json_props, "string_customer": strings, "date_quarters": dates,
    "agg_distincts": distincts, "filter_parts": filters, "array_heads": arrays, "map_codes": maps, "unpivot_totals": unpivoted, "pivot_flags": pivoted,
    "agg_median": quantiles, "udtf_zipf": zipf_table, "udaf_imbalance": imbalance, "setops_bag_equal": bag_equal,
    "stream_window_tumbling": stream_tumbling, "stream_window_sliding": stream_sliding, "stream_sessions": stream_session, "stream_enrich": stream_enrich, "stream_interval_pairs": stream_pairs, "observe_rows": observed_rows,
}

_ZIPF_CASE = ", ".join(str(sum(k**-1.2 for k in range(1, j + 1)) / sum(k**-1.2 for k in range(1, 21))) for j in range(1, 21))
_CLICKS = "c AS (SELECT user_id, ts, max(event_id) AS click_id FROM events WHERE event_type = 'click' GROUP BY 1, 2)"

ORACLES = {
    "rollup_flags": "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity::BIGINT)::BIGINT AS q FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "cube_orders": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "grouping_sets_events": "SELECT event_type, coalesce(user_id % 5, -1) AS g, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (user_id % 5), ())",
    "window_topk_orders": "SELECT * FROM (SELECT o_orderpriority, o_orderkey, round(o_totalprice, 2) AS price, row_number() OVER (PARTITION BY o_orderpriority ORDER BY round(o_totalprice, 2) DESC, o_orderkey) AS place FROM orders) WHERE place <= 3",
    "window_ranked_suppliers": "SELECT s_suppkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS qt FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_suppkey)",
    "window_running_events": """SELECT user_id, event_id, event_id % 11 AS v, sum(event_id % 11) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)::BIGINT AS run, coalesce(lag(event_id % 11) OVER w, -1) AS prev, coalesce(lead(event_id % 11) OVER w, -1) AS next,
  sum(event_id % 11) OVER (w ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING)::BIGINT AS three FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)""",
    "asof_click": f"WITH {_CLICKS} SELECT event_id, coalesce(click_id, -1) AS last_click FROM (SELECT * FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN c ON e.user_id = c.user_id AND e.ts >= c.ts",
    "interval_click": "SELECT x.event_id, y.event_id AS other_id FROM events x JOIN events y ON x.user_id = y.user_id AND abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 21600000000 WHERE x.event_type = 'purchase' AND y.event_type = 'click'",
    "range_join_bands": "SELECT CASE WHEN c_custkey < 100 THEN 0 WHEN c_custkey < 1000 THEN 1 ELSE 2 END::BIGINT AS band, count(*) AS n FROM customer WHERE c_custkey >= 0 AND c_custkey < 1000000 GROUP BY 1",
    "setops_intersect": "(SELECT l_linenumber::BIGINT AS key FROM lineitem GROUP BY 1 HAVING count(*) >= 0.1 * (SELECT count(*) FROM lineitem)) INTERSECT (SELECT turn FROM conversations GROUP BY 1 HAVING count(*) >= 0.1 * (SELECT count(*) FROM conversations))",
    "setops_except": "(SELECT l_linenumber::BIGINT AS key FROM lineitem GROUP BY 1 HAVING count(*) >= 0.1 * (SELECT count(*) FROM lineitem)) EXCEPT (SELECT turn FROM conversations GROUP BY 1 HAVING count(*) >= 0.1 * (SELECT count(*) FROM conversations))",
    "setops_union_distinct": "SELECT n_regionkey AS k FROM nation UNION SELECT r_regionkey FROM region",
    "json_keys": "SELECT k, count(*) AS n FROM (SELECT unnest(json_keys(props)) AS k FROM events) GROUP BY k",
    "string_customer": "SELECT c_custkey, upper(c_name) AS up, substr(c_name, 1, 4) AS head, length(c_name) AS len, regexp_replace(c_name, '[0-9]+', '#', 'g') AS masked, concat_ws('-', c_mktsegment, c_nationkey::VARCHAR) AS tag, md5(c_name) AS h FROM customer",
    "date_quarters": "SELECT year(l_shipdate) AS y, quarter(l_shipdate) AS q, count(*) AS n, max(date_diff('day', DATE '1995-01-01', l_shipdate::DATE)) AS last_day FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1997-01-01' GROUP BY 1, 2",
    "agg_distincts": "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT user_id % 10) AS pairs FROM events GROUP BY event_type",
    "filter_parts": "SELECT p_partkey, CASE WHEN p_size > 10 THEN 'big' ELSE 'small' END AS kind FROM part WHERE p_size BETWEEN 5 AND 15 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#13') AND p_type NOT LIKE '%TIN%' AND p_retailprice IS NOT NULL",
    "array_heads": "SELECT vec_id, len(embedding[1:3]) AS n, len(list_filter(embedding[1:3], lambda x: x > 0)) AS positive, len(list_filter(embedding[1:3], lambda x: x > 0)) > 0 AS any_positive FROM embeddings",
    "map_codes": "SELECT CASE event_type WHEN 'click' THEN 1 WHEN 'view' THEN 2 WHEN 'purchase' THEN 3 ELSE 0 END::BIGINT AS code, count(*) AS n FROM events GROUP BY 1",
    "unpivot_totals": "SELECT 'numbers' AS what, sum(l_linenumber)::BIGINT AS value FROM lineitem UNION ALL SELECT 'rows', count(*) FROM lineitem UNION ALL SELECT 'largest', max(l_orderkey) FROM lineitem",
    "pivot_flags": "SELECT l_returnflag, nullif(sum(CASE WHEN l_linestatus = 'F' THEN 1 ELSE 0 END), 0)::BIGINT AS \"F\", nullif(sum(CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END), 0)::BIGINT AS \"O\" FROM lineitem GROUP BY 1",
    "agg_median": "SELECT quantile_cont(o_custkey, 0.5)::DOUBLE AS median, min(o_custkey) AS low, max(o_custkey) AS high FROM orders",
    "udtf_zipf": f"SELECT least(20, len(list_filter([{_ZIPF_CASE}], lambda b: b <= (c_custkey * 7919 + 104729) % 1000003 / 1000003)) + 1)::BIGINT AS rank, count(*) AS n FROM customer GROUP BY 1",
    "udaf_imbalance": "SELECT round(max(n) / avg(n), 6) AS max_over_mean FROM (SELECT l_orderkey % 6 AS node, count(*) AS n FROM lineitem GROUP BY 1)",
    "setops_bag_equal": "SELECT o_orderkey, '' AS side FROM orders WHERE false",
    "stream_window_tumbling": "SELECT epoch(time_bucket(INTERVAL 1 DAY, ts))::BIGINT AS start, event_type AS key, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_window_sliding": "SELECT epoch(s)::BIGINT AS start, event_type AS key, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 1 DAY, ts), time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY]) AS s FROM events) GROUP BY 1, 2",
    "observe_rows": "SELECT count(*) AS n, sum(l_linenumber)::BIGINT AS total FROM lineitem WHERE l_quantity > 30",
    "stream_interval_pairs": """SELECT l.user_id, l.event_id, r.event_id AS right_event_id FROM events l JOIN events r ON l.user_id = r.user_id
AND r.ts >= l.ts AND r.ts <= l.ts + INTERVAL 10 MINUTE WHERE l.event_type IN ('view', 'click')""",
    "stream_sessions": """SELECT user_id AS key, sum(CASE WHEN prev IS NULL OR ts >= prev + INTERVAL 1 HOUR THEN 1 ELSE 0 END)::BIGINT AS sessions, count(*) AS n
FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS prev FROM events) GROUP BY 1""",
    "stream_enrich": "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1",
}
