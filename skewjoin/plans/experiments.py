"""The experiments, by name: each runs its configurations and returns one row per configuration and strategy.

measure: 'cost' (the model's moved, busiest, merged and total tuples, and the choice), 'load' (observed work of
the busiest node and its ratio to the mean) or 'time' (seconds and tuples per second of the routed join, with the
rows gathered where a gateway is named, and the regret of each strategy in seconds).
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.dispatch import CANDIDATES, choose, observe
from ..operators.merge import gather_others
from ..operators.routes import POLICIES
from ..operators.strategies import routed
from . import cost, metrics, workloads
from .workloads import Workload, literal, micro, intro

COST = "config string, strategy string, moved double, busiest double, merged double, total double, chosen boolean"
LOAD = "config string, strategy string, busiest_work long, all_work long, max_over_mean double"
TIME = "config string, strategy string, seconds double, tuples_per_s double, chosen boolean, regret double"


def costs(spark: SparkSession, sf_dir: str, configs, policies=CANDIDATES, form: str = "complete") -> DataFrame:
    """Each distinct input is profiled once."""
    seen: dict[Workload, cost.Profile] = {}
    rows = []
    for config, w, gateway in configs:
        if w not in seen:
            seen[w] = observe(w.sides(spark, sf_dir), w.p, w.n)[1]
        decision = choose(seen[w], gateway, form, policies)
        rows += [(str(config), name, *(round(float(v), 3) for v in parts), name == decision.strategy) for name, *parts in decision.costs]
    return spark.createDataFrame(rows, COST)


def loads(spark: SparkSession, sf_dir: str, configs, policies=CANDIDATES) -> DataFrame:
    """What the nodes really get and produce, cold keys included: one aggregation per strategy."""
    out = None
    for config, w, _ in configs:
        x = w.sides(spark, sf_dir)
        hot, _ = observe(x, w.p, w.n)
        for name in policies:
            work = metrics.node_load(x, hot, POLICIES[name], w.n).select((F.col("r_n") + F.col("s_n") + F.col("out_n")).alias("w"))
            row = work.agg(F.max("w").alias("busiest_work"), F.sum("w").alias("all_work")).select(
                F.lit(str(config)).alias("config"), F.lit(name).alias("strategy"), "busiest_work", "all_work",
                F.round(F.col("busiest_work") * w.n / F.col("all_work"), 6).alias("max_over_mean"),
            )
            out = row if out is None else out.unionByName(row)
    return out if out is not None else spark.createDataFrame([], LOAD)


def times(spark: SparkSession, sf_dir: str, configs, policies=CANDIDATES, runs: int = 3) -> DataFrame:
    """Seconds of the routed join, its pairs materialised into an aggregate, after gathering them where a gateway is
    named; the dispatcher's choice among the policies, and what its choice costs over the fastest one."""
    rows = []
    for config, w, gateway in configs:
        x = w.sides(spark, sf_dir)
        r, s = x.r.persist(), x.s.persist()
        size = r.count(), s.count()
        held = replace(x, r=r, s=s)
        hot, profile = observe(held, w.p, w.n)
        chosen = choose(profile, gateway, candidates=policies).strategy

        def pairs(name: str) -> DataFrame:
            joined = routed(held, hot, POLICIES[name], w.n).select("rh", "sh", "dst")
            if gateway is not None:
                joined = gather_others(joined, w.n, gateway)
            return joined.agg(F.count(F.lit(1)), F.sum(F.hash("rh", "sh").cast("long")))

        took = {name: metrics.timed(lambda name=name: pairs(name), runs)["median_s"] for name in policies}
        rows += [(str(config), name, t, metrics.throughput(*size, t), name == chosen, metrics.regret(name, took)) for name, t in took.items()]
        r.unpersist()
        s.unpersist()
    return spark.createDataFrame(rows, TIME)


def speedups(timed: DataFrame, base: int = 3) -> DataFrame:
    """(strategy, config, speedup): throughput over that of the same strategy on `base` nodes; configs are node numbers."""
    at = timed.where(F.col("config") == str(base)).select("strategy", F.col("tuples_per_s").alias("base"))
    return timed.join(at, "strategy").select("strategy", "config", (F.col("tuples_per_s") / F.col("base")).alias("speedup"))


def faster(timed: DataFrame) -> DataFrame:
    """(config, strategy, other, percent): by how many percent a strategy is faster than each other one."""
    other = timed.select("config", F.col("strategy").alias("other"), F.col("seconds").alias("other_s"))
    return timed.join(other, "config").where("strategy <> other").select("config", "strategy", "other", (100 * (F.col("other_s") / F.col("seconds") - 1)).alias("percent"))


def stabilities(results: DataFrame, column: str) -> DataFrame:
    """(strategy, stability): coefficient of variation of a measure over the configurations, as over seeds of a placement."""
    return results.groupBy("strategy").agg((F.stddev_pop(column) / F.avg(column)).alias("stability"))


def run(spark: SparkSession, sf_dir: str, configs, measure: str = "cost", policies=CANDIDATES, **options) -> DataFrame:
    return {"cost": costs, "load": loads, "time": times}[measure](spark, sf_dir, configs, policies, **options)


def w1_ratio(spark, sf_dir, ratios=workloads.RATIOS, nodes: int = 3, z: float = 1.2, **kw) -> DataFrame:
    """Size ratio of the two inputs."""
    return run(spark, sf_dir, [(k, Workload("zipf", nodes, 10_000 * k, 10_000, z=z), None) for k in ratios], **kw)


def w2_zipf(spark, sf_dir, zs=workloads.ZIPF_FACTORS, nodes: int = 3, **kw) -> DataFrame:
    """Zipf factor."""
    return run(spark, sf_dir, [(z, Workload("zipf", nodes, 293_000, 10_000, z=z), None) for z in zs], **kw)


def w3_scaleout(spark, sf_dir, nodes=workloads.NODES, z: float = 1.5, **kw) -> DataFrame:
    """Number of nodes."""
    return run(spark, sf_dir, [(n, Workload("zipf", n, 391_000, 19_000, z=z), None) for n in nodes], **kw)


def w4_threshold(spark, sf_dir, r_shares=workloads.SHARES, s_share: float = 0.5, p: float = 0.05, n: int = 12, place: str = "range_replica", **kw) -> DataFrame:
    """Share of the probe side's hot key, across the threshold."""
    return run(spark, sf_dir, [(h, Workload("single", n, 195_000, 147_000, r_hot=h, s_hot=s_share, p=p, place=place), None) for h in r_shares], **kw)


def w5_gateway(spark, sf_dir, gateways=tuple(range(12)), n: int = 12, **kw) -> DataFrame:
    """The node at which rows are gathered."""
    w = workloads.gateway_sweep()[0][1].with_(n=n)
    return run(spark, sf_dir, [(g, w, g) for g in gateways], **kw)


def w6_scenarios(spark, sf_dir, **kw) -> DataFrame:
    """Skew on one node; skew that is even already; the hot key's owner at the gateway."""
    return run(spark, sf_dir, workloads.scenarios(), **kw)


def w7_merge_kind(spark, sf_dir, gateway: int = 0, **kw) -> DataFrame:
    """One join whose rows are gathered, and the same join counted in place."""
    w = workloads.gateway_sweep()[0][1]
    return run(spark, sf_dir, [("rows", w, gateway), ("count", w, None)], **kw)


def w8_intro(spark, sf_dir="", **kw) -> DataFrame:
    return run(spark, sf_dir, [("intro", literal(intro(), 3, 0.5), None)], **kw)


def w9_micro(spark, sf_dir="", gateways=(0, 1, 2), **kw) -> DataFrame:
    return run(spark, sf_dir, [(g, literal(micro(), 3, 0.2), g) for g in gateways], **kw)


def w10_p_sweep(spark, sf_dir, ps=workloads.THRESHOLDS, **kw) -> DataFrame:
    """The threshold itself."""
    return run(spark, sf_dir, [(p, Workload("zipf", 3, 293_000, 10_000, z=1.2, p=p), None) for p in ps], **kw)


def w11_replica_seeds(spark, sf_dir, seeds=tuple(range(10)), **kw) -> DataFrame:
    """Which replicas the readers take."""
    return run(spark, sf_dir, [(s, w.with_(seed=s), None) for (_, w, _), s in zip(workloads.replica_seeds()[:1] * len(seeds), seeds)], **kw)


def w12_no_skew(spark, sf_dir, **kw) -> DataFrame:
    """No value reaches the threshold: all strategies are hashing."""
    return run(spark, sf_dir, [("no skew", Workload("zipf", 6, 195_000, 98_000, z=0.0), None)], **kw)


def w13_natural(spark, sf_dir, name: str = "lang", p: float = 0.12) -> DataFrame:
    """(key, pairs) of a given pair of tables with natural skew, through the public join."""
    from ..operators.dispatch import skew_join

    r, s = workloads.natural(spark, sf_dir, name)
    return skew_join(r, s, "a", "b", p=p, n=6).groupBy("a").agg(F.count(F.lit(1)).alias("pairs"))


def w14_filtered(spark, sf_dir, predicate: str = "r_qty <= 3") -> DataFrame:
    """Skewed values of the probe side before and after an atomic filter: (key, before, after)."""
    from . import stats

    w = Workload("zipf", 3, 293_000, 10_000, z=1.2)
    x = w.sides(spark, sf_dir)
    known = stats.exact_skew(x.r, "a", w.p / 2)
    after = stats.after_filter(x.r, "a", known, predicate, w.p)
    return known.select("key", F.col("cnt").alias("before")).join(after.select("key", F.col("cnt").alias("after")), "key")


def w15_intermediate(spark, sf_dir, p: float = 0.02, prefix_rows: int = 20_000) -> DataFrame:
    """Skewed values of a join's result, found in prefixes of its partitions while it is produced."""
    from ..sources.catalog import load
    from . import stats

    li, part = load(spark, sf_dir, "lineitem").select("l_partkey"), load(spark, sf_dir, "part").select("p_partkey", "p_size")
    joined = li.join(part, li.l_partkey == part.p_partkey).select(F.col("p_size").cast("long").alias("a"))
    return stats.runtime_skew(joined, "a", p, prefix_rows, verify=True)
