"""Skew statistics, classes and placement."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import classify, placement, stats
from ..plans.workloads import Workload, natural
from ..sources.catalog import load, shared_dir

_COLUMNS = {
    "event_type": ("events", "event_type", 0.2),
    "lang": ("documents", "lang", 0.1),
    "quality": ("labels", "quality", 0.2),
    "priority": ("orders", "o_orderpriority", 0.2),
}


def _values(table: str, column: str, p: float, strict: bool = False):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = stats.exact_skew(load(spark, sf_dir, table), column, p, strict)
        return out.select(F.col("key").cast("string").alias("key"), "cnt", "n_rows", F.round("share", 6).alias("share"))
    return run


def _values_sql(table: str, column: str, p: float, strict: bool = False) -> str:
    test = f"cnt > {p} * n_rows + 1e-9" if strict else f"cnt >= {p} * n_rows - 1e-9"
    return f"""SELECT key, cnt, n_rows, round(cnt / n_rows::DOUBLE, 6) AS share FROM (
  SELECT {column}::VARCHAR AS key, count(*) AS cnt, (SELECT count({column}) FROM {table}) AS n_rows FROM {table} WHERE {column} IS NOT NULL GROUP BY 1) t WHERE {test}"""


def _verified(detector, table: str = "lineitem", column: str = "l_linenumber", p: float = 0.12):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = detector(load(spark, sf_dir, table), column, p)
        return out.select(F.col("key").cast("string").alias("key"), "cnt", "n_rows", F.round("share", 6).alias("share"))
    return run


def sampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.sampled_skew(load(spark, sf_dir, "lineitem"), "l_linenumber", 0.12, 0.5, seed=3).select("key", "cnt", "n_rows")


_SAMPLED = Workload("zipf", 3, 293_000, 10_000, z=1.2, p=0.02)


def quality_of_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall, precision and count error of skew estimated from a fiftieth of the rows, against exact counts."""
    from ..plans.metrics import detector_quality

    r = _SAMPLED.sides(spark, sf_dir).r
    found = stats.hash_sampled_skew(r, "a", _SAMPLED.p, F.floor(F.col("rh") / 7), 50)
    out = detector_quality(found, stats.exact_skew(r, "a", _SAMPLED.p))
    return out.select(*[F.round(c, 9).alias(c) for c in out.columns])


_QUALITY_SQL = f"""WITH {_SAMPLED.ctes()},
t AS (SELECT * FROM r WHERE (rh // 7) % 50 = 0),
f AS (SELECT a AS key, 50 * count(*) AS f FROM t GROUP BY a HAVING count(*) >= {_SAMPLED.p} * (SELECT count(*) FROM t) - 1e-9),
e AS (SELECT a AS key, count(*) AS e FROM r GROUP BY a HAVING count(*) >= {_SAMPLED.p} * (SELECT count(*) FROM r) - 1e-9)
SELECT round(count(CASE WHEN f IS NOT NULL AND e IS NOT NULL THEN 1 END) / greatest(1.0, count(e))::DOUBLE, 9) AS recall,
       round(count(CASE WHEN f IS NOT NULL AND e IS NOT NULL THEN 1 END) / greatest(1.0, count(f))::DOUBLE, 9) AS precision,
       round(coalesce(avg(abs(f - e) / e::DOUBLE), 0), 9)::DOUBLE AS count_error
FROM f FULL JOIN e USING (key)"""


def composite(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = stats.exact_skew(load(spark, sf_dir, "lineitem"), stats.key_struct(["l_returnflag", "l_linestatus"]), 0.1)
    return out.select(F.col("key.l_returnflag").alias("flag"), F.col("key.l_linestatus").alias("status"), "cnt", "n_rows")


def with_nulls(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = load(spark, sf_dir, "orders").select(F.when(F.col("o_orderkey") % 10 != 0, F.col("o_custkey") % 7).alias("k"))
    return stats.exact_skew(df, "k", 0.1).select("key", "cnt", "n_rows")


def filtered(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = load(spark, sf_dir, "lineitem")
    known = stats.exact_skew(df, "l_linenumber", 0.05)
    return stats.after_filter(df, "l_linenumber", known, "l_shipdate >= timestamp'1995-01-01'", 0.12).select("key", "cnt", "n_rows")


def sidecar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Statistics written once, read for a higher threshold."""
    path = f"{shared_dir(spark)}/skew-sidecar"
    stats.save_skew(stats.exact_skew(load(spark, sf_dir, "documents"), "lang", 0.05), path, "documents", "lang", 0.05)
    return stats.load_skew(spark, path, "documents", "lang", 0.12).select("key", "cnt", "n_rows")


def _classes(name: str, p: float, tie: str = "probe"):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r, s = natural(spark, sf_dir, name)
        found = classify.classes(r, s, "a", "b", stats.exact_skew(r, "a", p), stats.exact_skew(s, "b", p), tie)
        return found.select(F.col("key").cast("string").alias("key"), "cls", "r_cnt", "s_cnt")
    return run


def _classes_sql(r: str, s: str, p: float, tie: str = "probe") -> str:
    test = ">=" if tie == "probe" else ">"
    return f"""WITH r AS ({r}), s AS ({s}),
rc AS (SELECT a AS key, count(*) AS c FROM r WHERE a IS NOT NULL GROUP BY a), sc AS (SELECT b AS key, count(*) AS c FROM s WHERE b IS NOT NULL GROUP BY b),
hr AS (SELECT key FROM rc WHERE c >= {p} * (SELECT sum(c) FROM rc) - 1e-9), hs AS (SELECT key FROM sc WHERE c >= {p} * (SELECT sum(c) FROM sc) - 1e-9)
SELECT hk.key::VARCHAR AS key, CASE WHEN hs.key IS NULL THEN 'PROBE_ONLY' WHEN hr.key IS NULL THEN 'BUILD_ONLY'
         WHEN coalesce(rc.c, 0) {test} coalesce(sc.c, 0) THEN 'BOTH_PROBE_HEAVY' ELSE 'BOTH_BUILD_HEAVY' END AS cls,
       coalesce(rc.c, 0) AS r_cnt, coalesce(sc.c, 0) AS s_cnt
FROM (SELECT key FROM hr UNION SELECT key FROM hs) hk LEFT JOIN hr USING (key) LEFT JOIN hs USING (key) LEFT JOIN rc USING (key) LEFT JOIN sc USING (key)"""


_LANG = ("SELECT lang AS a FROM documents", "SELECT lang AS b FROM documents")
_QT = ("SELECT quality AS a FROM labels", "SELECT toxic AS b FROM labels")
_LT = ("SELECT l_linenumber AS a FROM lineitem", "SELECT turn AS b FROM conversations")

_ZIPF = Workload("zipf", 3, 293_000, 10_000, z=1.2)


def classes_zipf(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = _ZIPF.sides(spark, sf_dir)
    return classify.classes(x.r, x.s, "a", "b", stats.exact_skew(x.r, "a", _ZIPF.p), stats.exact_skew(x.s, "b", _ZIPF.p))


def _place(w: Workload):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        x = w.sides(spark, sf_dir)
        r = placement.node_sizes(x.r).select(F.lit("probe").alias("side"), F.col("src").cast("long").alias("src"), "n")
        return r.union(placement.node_sizes(x.s).select(F.lit("build"), F.col("src").cast("long"), "n"))
    return run


def _place_sql(w: Workload) -> str:
    return f"WITH {w.ctes()} SELECT 'probe' AS side, src::BIGINT AS src, count(*) AS n FROM r GROUP BY src UNION ALL SELECT 'build', src::BIGINT, count(*) FROM s GROUP BY src"


_SINGLE = Workload("single", 12, 195_000, 147_000, r_hot=0.06, s_hot=0.5)


def hot_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tuples of the hot keys on each node: placement skew."""
    w = _SINGLE.with_(place="range_replica")
    x = w.sides(spark, sf_dir)
    out = placement.profile(x.r, "a", stats.exact_skew(x.r, "a", w.p))
    return out.select(F.col("src").cast("long").alias("src"), "key", "cnt")


def shipdate_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of each node before and after a filter: selectivity skew."""
    df = load(spark, sf_dir, "lineitem").withColumn("src", placement.range_replica(F.col("l_orderkey"), 6, 500, 1).cast("long"))
    return df.groupBy("src").agg(F.count(F.lit(1)).alias("n_all"), F.sum((F.col("l_shipdate") >= F.to_timestamp(F.lit("1997-01-01"))).cast("long")).alias("n_kept"))


QUERIES = {f"skew_values_{k}": _values(*v) for k, v in _COLUMNS.items()} | {
    "skew_boundary_ge": _values("nation", "n_regionkey", 0.2),
    "skew_boundary_gt": _values("nation", "n_regionkey", 0.2, True),
    "skew_sampled_candidates": sampled,
    "skew_freqitems_verified": _verified(stats.sketch_skew),
    "skew_topk_verified": _verified(stats.top_k_skew),
    "skew_runtime_verified": _verified(lambda df, k, p: stats.runtime_skew(df, k, p, 5000, verify=True)),
    "skew_detector_quality": quality_of_sample,
    "skew_composite_key": composite,
    "skew_null_key": with_nulls,
    "skew_after_filter": filtered,
    "skew_sidecar": sidecar,
    "classes_lang_self": _classes("lang", 0.12),
    "classes_quality_toxic": _classes("quality_toxic", 0.13),
    "classes_linenumber_turn": _classes("linenumber_turn", 0.15),
    "classes_tie": _classes("lang", 0.12, "build"),
    "classes_zipf12": classes_zipf,
    "place_even": _place(_SINGLE),
    "place_by_key": _place(_ZIPF.with_(place="by_key")),
    "place_range_replica": _place(_SINGLE.with_(place="range_replica", seed=3)),
    "place_hot_node": _place(_SINGLE.with_(place="hot_node", node=2)),
    "tps_profile": hot_profile,
    "ss_profile_shipdate": shipdate_profile,
}

ORACLES = {f"skew_values_{k}": _values_sql(*v) for k, v in _COLUMNS.items()} | {
    "skew_boundary_ge": _values_sql("nation", "n_regionkey", 0.2),
    "skew_boundary_gt": _values_sql("nation", "n_regionkey", 0.2, True),
    "skew_sampled_candidates": "SELECT l_linenumber AS key, count(*) AS cnt, (SELECT count(*) FROM lineitem) AS n_rows FROM lineitem GROUP BY 1 HAVING count(*) >= 0.12 * (SELECT count(*) FROM lineitem) - 1e-9",
    "skew_freqitems_verified": _values_sql("lineitem", "l_linenumber", 0.12),
    "skew_topk_verified": _values_sql("lineitem", "l_linenumber", 0.12),
    "skew_runtime_verified": _values_sql("lineitem", "l_linenumber", 0.12),
    "skew_detector_quality": _QUALITY_SQL,
    "skew_composite_key": "SELECT l_returnflag AS flag, l_linestatus AS status, count(*) AS cnt, (SELECT count(*) FROM lineitem) AS n_rows FROM lineitem GROUP BY 1, 2 HAVING count(*) >= 0.1 * (SELECT count(*) FROM lineitem) - 1e-9",
    "skew_null_key": "WITH k AS (SELECT CASE WHEN o_orderkey % 10 <> 0 THEN o_custkey % 7 END AS k FROM orders) SELECT k AS key, count(*) AS cnt, (SELECT count(k) FROM k) AS n_rows FROM k WHERE k IS NOT NULL GROUP BY k HAVING count(*) >= 0.1 * (SELECT count(k) FROM k) - 1e-9",
    "skew_after_filter": "WITH f AS (SELECT l_linenumber AS k FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01') SELECT k AS key, count(*) AS cnt, (SELECT count(*) FROM f) AS n_rows FROM f GROUP BY k HAVING count(*) >= 0.12 * (SELECT count(*) FROM f) - 1e-9",
    "skew_sidecar": "SELECT lang AS key, count(*) AS cnt, (SELECT count(lang) FROM documents) AS n_rows FROM documents WHERE lang IS NOT NULL GROUP BY lang HAVING count(*) >= 0.12 * (SELECT count(lang) FROM documents) - 1e-9",
    "classes_lang_self": _classes_sql(*_LANG, 0.12),
    "classes_quality_toxic": _classes_sql(*_QT, 0.13),
    "classes_linenumber_turn": _classes_sql(*_LT, 0.15),
    "classes_tie": _classes_sql(*_LANG, 0.12, "build"),
    "classes_zipf12": f"WITH {_ZIPF.ctes()}, {_ZIPF.class_ctes()} SELECT key, cls, rc AS r_cnt, sc AS s_cnt FROM cls",
    "place_even": _place_sql(_SINGLE),
    "place_by_key": _place_sql(_ZIPF.with_(place="by_key")),
    "place_range_replica": _place_sql(_SINGLE.with_(place="range_replica", seed=3)),
    "place_hot_node": _place_sql(_SINGLE.with_(place="hot_node", node=2)),
    "tps_profile": f"WITH {_SINGLE.with_(place='range_replica').ctes()}, t AS (SELECT a, count(*) AS c FROM r GROUP BY a HAVING count(*) >= 0.05 * (SELECT count(*) FROM r) - 1e-9) SELECT src::BIGINT AS src, r.a AS key, count(*) AS cnt FROM r JOIN t USING (a) GROUP BY 1, 2",
    "ss_profile_shipdate": "SELECT ((l_orderkey // 500) * 5 + ((((l_orderkey // 500) * 7919 + 104729) % 1000003) // 7) % 3) % 6 AS src, count(*) AS n_all, sum(CASE WHEN l_shipdate >= TIMESTAMP '1997-01-01' THEN 1 ELSE 0 END)::BIGINT AS n_kept FROM lineitem GROUP BY 1",
}
