"""The behaviour that the experiments report: which strategy wins, and how it moves with each parameter."""

import pytest
from pyspark.sql import functions as F

from skewjoin.operators import baselines
from skewjoin.plans import cost, workloads
from skewjoin.operators.dispatch import choose, observe
from skewjoin.operators.routes import POLICIES
from skewjoin.queries import cost_queries


def test_gateway_sweep_hash_wins_only_at_the_hot_keys_owner(spark, oracle_dir):
    rows = cost_queries.table(spark, oracle_dir, workloads.gateway_sweep()).where("chosen").collect()
    assert {int(r["config"]): r["strategy"] == "hash_all" for r in rows} == {g: g == 8 for g in range(12)}


def test_threshold_sweep_changes_its_winner_at_the_threshold(spark, oracle_dir):
    """With uneven placement: stay-and-replicate below p, four routes from p on."""
    rows = cost_queries.table(spark, oracle_dir, workloads.threshold_sweep()).where("chosen").collect()
    chosen = {float(r["config"]): r["strategy"] for r in rows}
    assert all(chosen[s] == "stay_replicate" for s in (0.01, 0.02, 0.03, 0.04))
    assert all(chosen[s] == "four_route" for s in (0.06, 0.07, 0.08, 0.09))


def test_busiest_node_grows_least_with_four_routes(spark, oracle_dir):
    """Along the Zipf sweep hashing's busiest node grows fastest; spreading divides the head's work by the nodes."""
    gain = []
    for _, w, _ in workloads.zipf_sweep(12)[3:]:
        _, profile = observe(w.sides(spark, oracle_dir), w.p, w.n)
        gain.append(cost.join_phase(profile, POLICIES["hash_all"]) / cost.join_phase(profile, POLICIES["four_route"]))
    assert all(g > 3 for g in gain)
    assert gain[-1] > gain[0]


def test_more_nodes_do_not_help_hashing(spark, oracle_dir):
    busiest = {}
    for n, w, _ in workloads.scaleout():
        _, profile = observe(w.sides(spark, oracle_dir), w.p, w.n)
        busiest[n] = {s: cost.join_phase(profile, POLICIES[s]) for s in ("hash_all", "four_route")}
    assert busiest[3]["hash_all"] / busiest[12]["hash_all"] < 1.5
    assert busiest[3]["four_route"] / busiest[12]["four_route"] > 3


def test_scenarios(spark, oracle_dir):
    """Skew on one node: four routes; skew that is even already: staying; owner at the gateway: hashing."""
    rows = cost_queries.QUERIES["dispatch_scenarios"](spark, oracle_dir).collect()
    chosen = {r["config"]: r["strategy"] for r in rows if r["chosen"]}
    assert chosen == {"one_node_skew": "four_route", "even_skew": "stay_replicate", "gateway_home": "hash_all"}
    _, w, gateway = workloads.scenarios()[2]
    _, profile = observe(w.sides(spark, oracle_dir), w.p, w.n)
    assert cost.merge_phase(profile, POLICIES["hash_all"], gateway) == 0
    assert choose(profile, (gateway + 1) % 3).strategy != "hash_all"


def test_counting_needs_no_merge(spark, oracle_dir):
    _, w, _ = workloads.gateway_sweep()[0]
    _, profile = observe(w.sides(spark, oracle_dir), w.p, w.n)
    hashed = cost.total(profile, POLICIES["hash_all"])
    assert hashed / cost.total(profile, POLICIES["four_route"]) > 5
    assert choose(profile).strategy != "hash_all"


def test_lower_threshold_catches_more(spark, oracle_dir):
    caught = [len(observe(w.sides(spark, oracle_dir), w.p, w.n)[0]) for _, w, _ in workloads.p_sweep()]
    assert caught == sorted(caught, reverse=True) and caught[0] > caught[-1]


def test_four_routes_don_t_depend_on_the_replicas_read(spark, oracle_dir):
    spread, stay = [], []
    for _, w, _ in workloads.replica_seeds()[:4]:
        _, profile = observe(w.sides(spark, oracle_dir), w.p, w.n)
        spread.append(cost.join_phase(profile, POLICIES["scatter_replicate"]))
        stay.append(cost.join_phase(profile, POLICIES["stay_replicate"]))
    assert len(set(spread)) == 1 and len(set(stay)) > 1
    assert max(spread) < min(stay)


def test_schedules_balance_buckets_but_not_a_single_key():
    weights = {i: w for i, w in enumerate([40, 30, 20, 10, 10, 10])}
    for plan in (baselines.lpt, baselines.multifit):
        load = [0] * 3
        for b, node in plan(weights, 3).items():
            load[node] += weights[b]
        assert max(load) == 40
    assert set(baselines.multifit({0: 5}, 2).values()) == {0}


def test_plans_do_what_they_say(spark, oracle_dir):
    """Routed joins add no exchange of their own after dealing; native hints are obeyed."""
    w = workloads.Workload("zipf", 3, 293_000, 10_000)
    x = w.sides(spark, oracle_dir)
    hot, _ = observe(x, w.p, w.n)
    from skewjoin.operators.strategies import routed

    plan = routed(x, hot, POLICIES["four_route"], 3)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") - plan.count("BroadcastExchange") == 2
    on = F.col("a") == F.col("b")
    assert "ShuffledHashJoin" in baselines.shuffled_hash(x.r, x.s, on)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in baselines.sort_merge(x.r, x.s, on)._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("kind", ["parquet", "orc", "json", "csv"])
def test_sources_and_sinks(spark, tmp_path, kind):
    from skewjoin.sources import catalog

    df = spark.range(20).withColumn("k", F.col("id") % 3)
    catalog.save(df, str(tmp_path / kind), kind)
    back = catalog.read(spark, str(tmp_path / kind), kind, df.schema if kind in ("csv", "json") else None)
    assert back.exceptAll(df).count() == 0 and back.count() == 20
    if kind in ("csv", "json"):
        with pytest.raises(ValueError):
            catalog.read(spark, str(tmp_path / kind), kind)


def test_experiments_by_name(spark, small):
    """Every experiment runs on the smallest tables; times only where asked for."""
    from skewjoin.plans import experiments as e

    for fn in (e.w6_scenarios, e.w7_merge_kind, e.w8_intro, e.w9_micro, e.w12_no_skew):
        assert fn(spark, small).where("chosen").count() >= 1
    assert e.w1_ratio(spark, small, (1, 10)).count() == 6 and e.w2_zipf(spark, small, (1.2,)).count() == 3
    assert e.w3_scaleout(spark, small, (3,), measure="load").count() == 3
    assert e.w4_threshold(spark, small, (0.06,)).count() == e.w5_gateway(spark, small, (0,)).count() == e.w10_p_sweep(spark, small, (0.1,)).count() == 3
    assert e.w11_replica_seeds(spark, small, (0, 1)).count() == 6
    assert e.w13_natural(spark, small).count() == 4 and e.w14_filtered(spark, small).count() and e.w15_intermediate(spark, small).count()
    timed = e.w6_scenarios(spark, small, measure="time", runs=1)
    rows = timed.collect()
    assert len(rows) == 9 and all(r["seconds"] > 0 and r["regret"] >= 1 for r in rows) and sum(r["chosen"] for r in rows) == 3
    assert e.faster(spark.createDataFrame(rows)).count() == 18
    two = spark.createDataFrame([("3", "a", 2.0, 10.0), ("12", "a", 1.0, 25.0)], "config string, strategy string, seconds double, tuples_per_s double")
    assert {r["config"]: r["speedup"] for r in e.speedups(two).collect()} == {"3": 1.0, "12": 2.5}
    none = {r["strategy"]: r["busiest_work"] for r in e.w12_no_skew(spark, small, measure="load").collect()}
    assert len(set(none.values())) == 1


def test_adaptive_settings_are_put_back(spark):
    name = "spark.sql.adaptive.skewJoin.skewedPartitionFactor"
    before = spark.conf.get(name)
    with baselines.aqe_settings(spark, "64KB", 2.0):
        assert float(spark.conf.get(name)) == 2.0
    assert spark.conf.get(name) == before
