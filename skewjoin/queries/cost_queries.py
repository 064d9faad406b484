"""Costs and the dispatcher's choices over the experiment sweeps."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.dispatch import CANDIDATES, CANDIDATES_GRID, observe
from ..plans import cost, experiments, metrics, workloads
from ..plans.workloads import Workload, micro, repeated
from . import sqltext

ALL = ("stay_replicate", "four_route", "hash_all", "scatter_replicate", "grid", "subset_replicate")


table = experiments.costs


_W4, _W5 = workloads.threshold_sweep(), workloads.gateway_sweep()
_W6 = workloads.scenarios()
_ONE = [(0, Workload("single", 12, 195_000, 98_000, r_hot=0.1, s_hot=0.03, p=0.02, place="range_replica"), 4)]
_COUNT = [(g if g is not None else "count", w, g) for _, w, g in _W5[:1]] + [("count", _W5[0][1], None)]

SWEEPS = {
    "dispatch_ratio_sweep": (workloads.ratio_sweep(), CANDIDATES, "complete"),
    "dispatch_ratio_sweep_6": (workloads.ratio_sweep(6), CANDIDATES, "complete"),
    "dispatch_ratio_sweep_12": (workloads.ratio_sweep(12), CANDIDATES, "complete"),
    "dispatch_zipf_sweep": (workloads.zipf_sweep(), CANDIDATES, "complete"),
    "dispatch_zipf_sweep_6": (workloads.zipf_sweep(6), CANDIDATES, "complete"),
    "dispatch_zipf_sweep_12": (workloads.zipf_sweep(12), CANDIDATES, "complete"),
    "dispatch_scaleout": (workloads.scaleout(), CANDIDATES, "complete"),
    "dispatch_threshold_sweep": (_W4, CANDIDATES, "complete"),
    "dispatch_threshold_sweep_printed": (_W4, CANDIDATES, "printed"),
    "dispatch_threshold_even": (workloads.threshold_sweep("even"), CANDIDATES, "complete"),
    "dispatch_threshold_grid": (_W4, CANDIDATES_GRID, "complete"),
    "dispatch_gateway_sweep": (_W5, CANDIDATES, "complete"),
    "dispatch_scenarios": (_W6, CANDIDATES, "complete"),
    "dispatch_p_sweep": (workloads.p_sweep(), CANDIDATES, "complete"),
    "dispatch_replica_seeds": (workloads.replica_seeds(), CANDIDATES, "complete"),
    "dispatch_merge_kind": (_COUNT, CANDIDATES, "complete"),
    "cost_total_complete": (_ONE, ALL, "complete"),
    "cost_total_printed": (_ONE, ALL, "printed"),
    "cost_micro": ([(g, repeated(micro(), 3, 0.2), g) for g in range(3)], ALL, "complete"),
    "cost_micro_printed": ([(g, repeated(micro(), 3, 0.2), g) for g in range(3)], CANDIDATES, "printed"),
    "cost_grid": ([(n, Workload("single", n, 195_000, 98_000, r_hot=0.1, s_hot=0.1), 0) for n in (3, 6, 12)], ("grid", "scatter_replicate"), "complete"),
}


def _sweep(name: str):
    configs, policies, form = SWEEPS[name]
    return lambda spark, sf_dir: table(spark, sf_dir, configs, policies, form)


def _only(name: str, column: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _sweep(name)(spark, sf_dir).select("config", "strategy", column)
    return run


def regret(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Total cost of each strategy, taken always, over that of the best one, along the threshold and gateway sweeps;
    and which one the dispatcher takes."""
    return _regret(_sweep("dispatch_threshold_sweep")(spark, sf_dir), "threshold").union(_regret(_sweep("dispatch_gateway_sweep")(spark, sf_dir), "gateway"))


def _regret(t: DataFrame, sweep: str) -> DataFrame:
    best = t.groupBy("config").agg(F.min("total").alias("best"))
    return t.join(best, "config").select(F.lit(sweep).alias("sweep"), "config", "strategy", F.round(F.col("total") / F.col("best"), 6).alias("regret"), "chosen")


def stability(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Variation of each strategy's busiest node and total over the replicas that are read."""
    t = _sweep("dispatch_replica_seeds")(spark, sf_dir)
    out = [experiments.stabilities(t, c).select("strategy", F.lit(c).alias("measure"), F.round("stability", 9).alias("stability")) for c in ("busiest", "total")]
    return out[0].union(out[1])


def case_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Worst-node bounds of one hot key in both textbook situations."""
    w = Workload("single", 12, 195_000, 98_000, r_hot=0.1, s_hot=0.03, p=0.02)
    x = w.sides(spark, sf_dir)
    _, profile = observe(x, w.p, w.n)
    hot = profile.loads[0]
    total = x.r.count()
    share = max(hot.s_at)
    rows = [
        (case, s, round(float(cost.case_bound(case, s, hot.r, hot.s, w.n, hot.r_at, hot.s_at, total, share)), 3))
        for case in ("own_node", "spread") for s in CANDIDATES
    ]
    return spark.createDataFrame(rows, "situation string, strategy string, bound double")


_CB = Workload("single", 12, 195_000, 98_000, r_hot=0.1, s_hot=0.03, p=0.02)
_CASE_SQL = f"""WITH {_CB.ctes()},
v AS (SELECT (SELECT count(*) FROM r WHERE a = 7)::DOUBLE AS rx, (SELECT count(*) FROM s WHERE b = 7)::DOUBLE AS sx, (SELECT count(*) FROM r) AS rt,
  (SELECT max(c) FROM (SELECT count(*) AS c FROM r WHERE a = 7 GROUP BY src))::DOUBLE AS rm, (SELECT max(c) FROM (SELECT count(*) AS c FROM s WHERE b = 7 GROUP BY src))::DOUBLE AS sm)
SELECT situation, strategy, round(CASE WHEN situation = 'own_node' THEN CASE strategy WHEN 'stay_replicate' THEN sm ELSE sx END + rt / 12.0
  WHEN strategy = 'hash_all' THEN rx + sx + rx * sx WHEN strategy = 'stay_replicate' THEN sm + rm + sm * rm ELSE sm + rx / 12 + sm * (rx / 12) END, 3) AS bound
FROM v, (SELECT unnest(['own_node', 'spread']) AS situation), (SELECT unnest(['stay_replicate', 'four_route', 'hash_all']) AS strategy)"""


def observed_against_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Skewed tuples observed to move under hash_all and stay_replicate, beside the exact model."""
    w = _ONE[0][1]
    x = w.sides(spark, sf_dir)
    hot, profile = observe(x, w.p, w.n)
    keys = [h.key for h in hot]
    from ..operators.routes import POLICIES

    only = replace(x, r=x.r.where(F.col("a").isin(*keys)), s=x.s.where(F.col("b").isin(*keys)))
    out = None
    for name in ("hash_all", "stay_replicate"):
        seen = metrics.moved(only, hot, POLICIES[name], w.n).agg(F.sum("moved").alias("observed"))
        row = seen.select(F.lit(name).alias("strategy"), "observed", F.lit(int(cost.redistribution(profile, POLICIES[name], exact=True))).cast("long").alias("model"))
        out = row if out is None else out.union(row)
    return out


_OBS = _ONE[0][1]
_OBSERVED_SQL = " UNION ALL ".join(
    f"""SELECT '{p}' AS strategy, m::BIGINT AS observed, m::BIGINT AS model FROM (WITH {sqltext.routed(_OBS, p)}
SELECT (SELECT count(*) FROM rd JOIN cls ON a = key WHERE dst <> src) + (SELECT count(*) FROM sd JOIN cls ON b = key WHERE dst <> src) AS m) t"""
    for p in ("hash_all", "stay_replicate")
)

LOADS = {
    "load_scenarios": workloads.scenarios(),
    "load_scaleout": workloads.scaleout(),
    "load_ratio": workloads.ratio_sweep(6),
    "load_no_skew": [("no skew", Workload("zipf", 6, 195_000, 98_000, z=0.0), None)],
}


def _loads(name: str):
    return lambda spark, sf_dir: experiments.loads(spark, sf_dir, LOADS[name], ("hash_all", "stay_replicate", "four_route"))


def filtered_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return experiments.w14_filtered(spark, sf_dir)


_FW = Workload("zipf", 3, 293_000, 10_000, z=1.2)
_FILTERED_SQL = f"""WITH {_FW.ctes()},
k AS (SELECT a AS key, count(*) AS before FROM r GROUP BY a HAVING count(*) >= {_FW.p / 2} * (SELECT count(*) FROM r) - 1e-9),
f AS (SELECT a AS key, count(*) AS after FROM r WHERE r_qty <= 3 GROUP BY a HAVING count(*) >= {_FW.p} * (SELECT count(*) FROM r WHERE r_qty <= 3) - 1e-9)
SELECT key, before, after FROM k JOIN f USING (key)"""

QUERIES = {name: _loads(name) for name in LOADS} | {"skew_before_after_filter": filtered_counts} | {name: _sweep(name) for name in SWEEPS} | {
    "cost_re": _only("cost_total_complete", "moved"),
    "cost_comp": _only("cost_total_complete", "busiest"),
    "cost_summ_gather": _only("cost_total_complete", "merged"),
    "dispatch_regret": regret,
    "dispatch_stability": stability,
    "cost_case_bounds": case_bounds,
    "cost_observed": observed_against_model,
}

ORACLES = {name: sqltext.loads(c, ("hash_all", "stay_replicate", "four_route")) for name, c in LOADS.items()} | {"skew_before_after_filter": _FILTERED_SQL} | {name: sqltext.sweep(*args) for name, args in SWEEPS.items()} | {
    "cost_re": f"SELECT config, strategy, moved FROM ({sqltext.sweep(*SWEEPS['cost_total_complete'])})",
    "cost_comp": f"SELECT config, strategy, busiest FROM ({sqltext.sweep(*SWEEPS['cost_total_complete'])})",
    "cost_summ_gather": f"SELECT config, strategy, merged FROM ({sqltext.sweep(*SWEEPS['cost_total_complete'])})",
    "dispatch_regret": " UNION ALL ".join(
        f"SELECT '{name}' AS sweep, config, strategy, round(total / min(total) OVER (PARTITION BY config), 6) AS regret, chosen FROM ({sqltext.sweep(*SWEEPS[f'dispatch_{name}_sweep'])})"
        for name in ("threshold", "gateway")
    ),
    "dispatch_stability": " UNION ALL ".join(
        f"SELECT strategy, '{c}' AS measure, round(stddev_pop({c}) / avg({c}), 9) AS stability FROM ({sqltext.sweep(*SWEEPS['dispatch_replica_seeds'])}) GROUP BY strategy"
        for c in ("busiest", "total")
    ),
    "cost_case_bounds": _CASE_SQL,
    "cost_observed": _OBSERVED_SQL,
}
