"""The joins that the strategies are compared with, on the same inputs."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, strategies
from ..operators.alike import ROWS_R, ROWS_S, grouped, pairs, total
from ..plans.workloads import Workload
from ..sources.catalog import load
from .join_queries import SINGLE, ZIPF, _per_key_sql, per_key


#: Rows of a key fall into so many groups by their hash: a multiple of the numbers of salts.
GROUPS = 24


def _grouped(w: Workload, spark: SparkSession, sf_dir: str) -> tuple[strategies.Sides, DataFrame]:
    """(the sides with rows grouped by key and hash, the probe side's rows): only counts and sums of the pairs are wanted."""
    x = w.sides(spark, sf_dir)
    r = grouped(x.r.withColumn("rh", F.col("rh") % GROUPS), ["a", "rh"], ROWS_R, ["r_qty"])
    s = grouped(x.s.withColumn("sh", F.col("sh") % GROUPS), ["b", "sh"], ROWS_S, ["s_pri"])
    return replace(x, r=r, s=s), x.r


def _simple(make, w: Workload = ZIPF):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return per_key(make(*_grouped(w, spark, sf_dir)))
    return run


_ON = lambda: F.col("a") == F.col("b")


def hinted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Join strategy by SQL hint over temporary views."""
    x, _ = _grouped(ZIPF, spark, sf_dir)
    x.r.createOrReplaceTempView("hinted_probe")
    x.s.createOrReplaceTempView("hinted_build")
    return per_key(spark.sql("SELECT /*+ SHUFFLE_HASH(s) */ * FROM hinted_probe r JOIN hinted_build s ON r.a = s.b"))


def nested(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A condition without an equality over two whole tables: customers and the suppliers not far from them by nation."""
    c = grouped(load(spark, sf_dir, "customer"), ["c_nationkey"], ROWS_R, ["c_custkey"])
    s = grouped(load(spark, sf_dir, "supplier"), ["s_nationkey"], ROWS_S, ["s_suppkey"])
    near = (F.col("c_nationkey") >= F.col("s_nationkey") - 1) & (F.col("c_nationkey") <= F.col("s_nationkey") + 1)
    out = baselines.nested_loop(c, s, near)
    return out.groupBy(F.col("c_nationkey").cast("long").alias("key")).agg(pairs().alias("pairs"), total("c_custkey", "r").alias("sum_r"), total("s_suppkey", "s").alias("sum_s"))


_NESTED_SQL = """SELECT c_nationkey::BIGINT AS key, count(*) AS pairs, sum(c_custkey)::BIGINT AS sum_r, sum(s_suppkey)::BIGINT AS sum_s
FROM customer JOIN supplier ON c_nationkey BETWEEN s_nationkey - 1 AND s_nationkey + 1 GROUP BY 1"""

QUERIES = {
    "base_shj": _simple(lambda x, rows: baselines.shuffled_hash(x.r, x.s, _ON())),
    "base_smj": _simple(lambda x, rows: baselines.sort_merge(x.r, x.s, _ON())),
    "base_bhj": _simple(lambda x, rows: baselines.broadcast_all(x.r, x.s, _ON())),
    "base_nlj": nested,
    "base_aqe": _simple(lambda x, rows: baselines.aqe_skew(x.r, x.s, _ON())),
    "base_salted": _simple(lambda x, rows: baselines.salted(x.r, x.s, "a", "b", 4, F.col("rh"))),
    "base_salted_hot": _simple(lambda x, rows: baselines.salted(x.r, x.s, "a", "b", 8, F.col("rh"), [1, 2, 3])),
    "base_range_split": _simple(lambda x, rows: baselines.range_split(x.r, x.s, "a", "b", 6, F.col("rh"), rows=rows)),
    "base_lpt": _simple(lambda x, rows: baselines.bucket_lpt(x.r, x.s, "a", "b", 6, rows=(ROWS_R, ROWS_S))),
    "base_multifit": _simple(lambda x, rows: baselines.bucket_multifit(x.r, x.s, "a", "b", 6, rows=(ROWS_R, ROWS_S))),
    "base_range_split_single": _simple(lambda x, rows: baselines.range_split(x.r, x.s, "a", "b", 12, F.col("rh"), rows=rows), SINGLE),
    "base_sql_hint": hinted,
}

ORACLES = {name: _per_key_sql(SINGLE if name == "base_range_split_single" else ZIPF) for name in QUERIES} | {"base_nlj": _NESTED_SQL}
