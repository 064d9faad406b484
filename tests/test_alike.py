"""Queries that count and sum a join's pairs, on inputs whose pairs nothing could make one by one."""

from threading import Timer

import pytest
from pyspark.sql import functions as F

from oracle import assert_same
from skewjoin.operators.strategies import Sides
from skewjoin.plans.workloads import Workload
from skewjoin.queries import baseline_queries, join_queries

R, S = 3_000_000, 2_000_000
NAMES = [n for n in baseline_queries.QUERIES if n != "base_nlj"] + [
    "join_auto_grid_candidate", "join_auto_zipf", "join_branches_hash_all", "join_branches_stay_replicate_grid", "join_flow_runtime", "join_flow_stats", "join_null_keys",
    "join_per_value", "join_four_route_zipf", "join_grid_single",
]


@pytest.fixture
def stopped(spark):
    """Jobs are cancelled after a while, so that a query that makes every pair fails."""
    timer = Timer(100, spark.sparkContext.cancelAllJobs)
    timer.start()
    yield
    timer.cancel()


def heavy(self, spark, sf_dir):
    """One key with all rows but a few: 6 * 10^12 pairs."""
    r = spark.range(0, R, 1, 8).select(F.when(F.col("id") < 10, F.col("id") + 100).otherwise(1).cast("long").alias("a"), F.col("id").alias("rh"), (F.col("id") % 7).alias("r_qty"), (F.col("id") % self.n).cast("int").alias("src"))
    s = spark.range(0, S, 1, 8).select(F.when(F.col("id") < 10, F.col("id") + 105).otherwise(1).cast("long").alias("b"), F.col("id").alias("sh"), (F.col("id") % 5).alias("s_pri"), (F.col("id") % self.n).cast("int").alias("src"))
    return Sides(r, s, "a", "b", F.col("rh"), F.col("sh"), "src", "src", home="example")


@pytest.mark.parametrize("name", NAMES)
def test_one_key_has_nearly_all_rows(spark, monkeypatch, stopped, name):
    monkeypatch.setattr(Workload, "sides", heavy)
    queries = baseline_queries.QUERIES | join_queries.QUERIES
    got = {r["key"]: (r["pairs"], r["sum_r"], r["sum_s"]) for r in queries[name](spark, "").collect()}
    gone = (lambda i: i % 10 == 0) if name == "join_null_keys" else (lambda i: False)  # that query drops keys by their hash
    kept = [[i for i in range(10, n) if not gone(i)] for n in (R, S)]
    want = {1: (len(kept[0]) * len(kept[1]), sum(i % 7 for i in kept[0]) * len(kept[1]), sum(i % 5 for i in kept[1]) * len(kept[0]))}
    want |= {100 + i: (1, i % 7, (i - 5) % 5) for i in range(5, 10) if not gone(i) and not gone(i - 5)}
    assert got == want


@pytest.fixture(scope="module")
def large(spark, tmp_path_factory):
    """Tables of few keys: up to 10^11 pairs."""
    d = tmp_path_factory.mktemp("large")
    i = F.col("id")
    tables = {
        "lineitem": spark.range(0, 1_000_000).select(i.alias("l_orderkey"), (i % 1000).alias("l_partkey"), (i % 77).alias("l_suppkey"), (i % 7 + 1).cast("int").alias("l_linenumber"), (i % 50 + 1).cast("double").alias("l_quantity")),
        "orders": spark.range(0, 1_000_000).select(i.alias("o_orderkey"), (i % 600).alias("o_custkey"), F.concat(F.lit("p"), i % 5).alias("o_orderpriority")),
        "customer": spark.range(0, 1_000_000).select(i.alias("c_custkey"), (i % 25).cast("int").alias("c_nationkey")),
        "supplier": spark.range(0, 500_000).select(i.alias("s_suppkey"), (i % 25).cast("int").alias("s_nationkey")),
        "part": spark.range(0, 500_000).select(i.alias("p_partkey"), (i % 50 + 1).cast("int").alias("p_size")),
        "events": spark.range(0, 1_000_000).select(i.alias("event_id"), F.concat(F.lit("p"), i % 4).alias("event_type")),
    }
    for name, df in tables.items():
        df.coalesce(1).write.parquet(f"{d}/raw/{name}")
        part = next(p for p in (d / "raw" / name).iterdir() if p.name.endswith(".parquet"))
        (d / f"{name}.parquet").symlink_to(part)
    for name in ("region", "nation", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"):
        (d / f"{name}.parquet").symlink_to(f"/root/testdata/sf0.001/{name}.parquet")
    return str(d)


_SUMS = """SELECT c_nationkey::BIGINT AS key, (c.n * sum(s.n))::BIGINT AS pairs, (c.v * sum(s.n))::BIGINT AS sum_r, (c.n * sum(s.v))::BIGINT AS sum_s
FROM (SELECT c_nationkey, count(*) AS n, sum(c_custkey) AS v FROM customer GROUP BY 1) c JOIN (SELECT s_nationkey, count(*) AS n, sum(s_suppkey) AS v FROM supplier GROUP BY 1) s
ON c_nationkey BETWEEN s_nationkey - 1 AND s_nationkey + 1 GROUP BY c_nationkey, c.n, c.v"""


@pytest.mark.parametrize("name", ["join_natural_quantity_size", "join_natural_type_priority", "join_intermediate_input", "base_nlj"])
def test_tables_of_few_keys(spark, large, stopped, name):
    queries, sql = baseline_queries.QUERIES | join_queries.QUERIES, join_queries.ORACLES | {"base_nlj": _SUMS}
    assert_same(queries[name](spark, large), sql[name], large)


@pytest.mark.parametrize("how", join_queries.HOWS)
def test_other_join_types_of_few_keys(spark, large, stopped, how):
    got = {r["k"]: r["n"] for r in join_queries.QUERIES[f"join_16_parts_{how}"](spark, large).collect()}
    r, s = [0] * 11, [0] * 11
    for i in range(1_000_000):
        r[i % 7 + 1] += 1
        s[i % 11] += i % 25 < 8
    if how in ("left_semi", "left_anti"):
        want = {k: r[k] for k in range(11) if r[k] and (s[k] > 0) == (how == "left_semi")}
    else:
        want = {k: (r[k] or 1) * (s[k] or 1) for k in range(11) if (r[k] or how in ("right", "full")) and (s[k] or how in ("left", "full"))}
    assert got == want
