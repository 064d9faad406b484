"""Measures: observed movement and load, throughput, stability, quality of detection and choice."""

from __future__ import annotations

from collections.abc import Callable
from statistics import mean, median, pstdev
from time import perf_counter

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.routes import Policy, send
from ..operators.strategies import Sides
from ..sources.catalog import consume
from .classify import HotKey


def sent(x: Sides, hot: list[HotKey], policy: Policy, n: int) -> tuple[DataFrame, DataFrame]:
    """The copies that each side sends, with their source `src` and destination `dst` among n nodes."""
    r, s = (df.withColumn("src", x.src(side, n)) for df, side in ((x.r, "probe"), (x.s, "build")))
    return (
        send(r, "probe", x.a, hot, policy, n, x.r_hash, owner=x.owner(F.col(x.a), n)),
        send(s, "build", x.b, hot, policy, n, x.s_hash, owner=x.owner(F.col(x.b), n)),
    )


def moved(x: Sides, hot: list[HotKey], policy: Policy, n: int) -> DataFrame:
    """(side, moved): copies that leave their node."""
    r, s = sent(x, hot, policy, n)
    both = r.select(F.lit("probe").alias("side"), "src", "dst").union(s.select(F.lit("build").alias("side"), "src", "dst"))
    return both.groupBy("side").agg(F.sum((F.col("dst") != F.col("src")).cast("long")).alias("moved"))


def node_load(x: Sides, hot: list[HotKey], policy: Policy, n: int) -> DataFrame:
    """(dst, r_n, s_n, out_n): what each node receives and produces, from counts per (node, key)."""
    r, s = sent(x, hot, policy, n)
    rk = r.groupBy("dst", F.col(x.a).alias("key")).agg(F.count(F.lit(1)).alias("r"))
    sk = s.groupBy("dst", F.col(x.b).alias("key")).agg(F.count(F.lit(1)).alias("s"))
    both = rk.join(sk, ["dst", "key"], "full").fillna(0, ["r", "s"])
    return both.groupBy("dst").agg(F.sum("r").alias("r_n"), F.sum("s").alias("s_n"), F.sum(F.col("r") * F.col("s")).alias("out_n"))


def worst_node(load: DataFrame) -> DataFrame:
    """The busiest node: (dst, work)."""
    w = load.select("dst", (F.col("r_n") + F.col("s_n") + F.col("out_n")).alias("work"))
    return w.orderBy(F.desc("work"), "dst").limit(1)


def imbalance(load: DataFrame, column: str, n: int) -> DataFrame:
    """(column, max_over_mean) over n nodes; nodes without rows count as 0."""
    return load.agg((F.max(column) * n / F.sum(column)).alias("max_over_mean")).select(F.lit(column).alias("measure"), "max_over_mean")


@F.pandas_udf(T.DoubleType())
def imbalance_udaf(v: pd.Series) -> float:
    """max / mean of a group as a grouped aggregate."""
    return float(v.max() / v.mean()) if len(v) and v.mean() else 0.0


def tps(df: DataFrame, n: int) -> DataFrame:
    """Tuple placement skew: rows per node before the join, as max over mean."""
    return imbalance(df.groupBy("src").agg(F.count(F.lit(1)).alias("tuple_placement")), "tuple_placement", n)


def ss(df: DataFrame, predicate: str, n: int) -> DataFrame:
    """Selectivity skew: rows per node that pass a filter."""
    kept = df.groupBy("src").agg(F.sum(F.expr(predicate).cast("long")).alias("selectivity"))
    return imbalance(kept, "selectivity", n)


def rs(load: DataFrame, n: int) -> DataFrame:
    """Redistribution skew: tuples received per node."""
    return imbalance(load.select((F.col("r_n") + F.col("s_n")).alias("redistribution")), "redistribution", n)


def jps(load: DataFrame, n: int) -> DataFrame:
    """Join product skew: results per node."""
    return imbalance(load.select(F.col("out_n").alias("join_product")), "join_product", n)


def cold_volume(n_cold_r: int, n_cold_s: int, n: int) -> float:
    """Tuples that every strategy moves for keys that are not skewed."""
    return (n_cold_r + n_cold_s) * (n - 1) / n


def timed(make: Callable[[], DataFrame], runs: int = 3) -> dict[str, float]:
    took = []
    for _ in range(runs):
        began = perf_counter()
        consume(make())
        took.append(perf_counter() - began)
    return {"median_s": median(took), "mean_s": mean(took), "min_s": min(took)}


def throughput(n_r: int, n_s: int, seconds: float, n_out: int = 0) -> float:
    """Tuples per second; give n_out to count results as well."""
    return (n_r + n_s + n_out) / seconds


def faster_pct(a_seconds: float, b_seconds: float) -> float:
    """By how many percent a is faster than b."""
    return 100.0 * (b_seconds / a_seconds - 1)


def speedup(per_nodes: dict[int, float], base: int = 3) -> dict[int, float]:
    """Throughputs relative to that on `base` nodes."""
    return {n: v / per_nodes[base] for n, v in per_nodes.items()}


def stability(values: list[float]) -> float:
    """Coefficient of variation."""
    return pstdev(values) / mean(values) if values and mean(values) else 0.0


def regret(chosen: str, costs: dict[str, float]) -> float:
    """Cost of the choice over the best one's; 1 is perfect."""
    best = min(costs.values())
    return costs[chosen] / best if best else 1.0


def dispatch_overhead(decision_seconds: float, whole_seconds: float) -> float:
    """Share of a run that choosing the strategy takes."""
    return overhead_share(decision_seconds, whole_seconds)


def detect_overhead(detect_seconds: float, whole_seconds: float) -> float:
    """Share of a run that finding the skewed values takes."""
    return overhead_share(detect_seconds, whole_seconds)


def overhead_share(part_seconds: float, whole_seconds: float) -> float:
    return part_seconds / whole_seconds if whole_seconds else 0.0


def detector_quality(found: DataFrame, exact: DataFrame) -> DataFrame:
    """(recall, precision, count_error) of a detector against exact statistics."""
    f = found.select("key", F.col("cnt").cast("double").alias("f"))
    e = exact.select("key", F.col("cnt").cast("double").alias("e"))
    j = f.join(e, "key", "full")
    return j.agg(
        (F.sum((F.col("f").isNotNull() & F.col("e").isNotNull()).cast("double")) / F.greatest(F.lit(1.0), F.sum(F.col("e").isNotNull().cast("double")))).alias("recall"),
        (F.sum((F.col("f").isNotNull() & F.col("e").isNotNull()).cast("double")) / F.greatest(F.lit(1.0), F.sum(F.col("f").isNotNull().cast("double")))).alias("precision"),
        F.coalesce(F.avg(F.abs(F.col("f") - F.col("e")) / F.col("e")), F.lit(0.0)).alias("count_error"),
    )
