"""The worked example, invariants of routing, degenerate inputs, random inputs."""

import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from skewjoin.operators.dispatch import choose, choose_per_value, observe, profile_of, skew_join
from skewjoin.operators.routes import HASH, POLICIES, REPLICATE, Policy, fan_out, grid_shape, partition, send
from skewjoin.operators.strategies import Sides, branches, routed
from skewjoin.plans import classify, cost, metrics, stats
from skewjoin.plans.classify import BOTH_PROBE, BUILD_ONLY, PROBE_ONLY, HotKey
from skewjoin.plans.workloads import intro, literal_sides, micro


def sides(spark, r, s):
    return literal_sides(spark, (r, s))


def pairs(df):
    return Counter((x["rh"], x["sh"]) for x in df.select("rh", "sh").collect())


def expected(r, s):
    return Counter((i, j) for i, (a, _) in enumerate(r) for j, (b, _) in enumerate(s) if a == b and a is not None)


@pytest.fixture(scope="module")
def example(spark):
    x = literal_sides(spark, micro())
    hot, profile = observe(x, 0.2, 3)
    return x, hot, profile


def test_example_classes(example):
    _, hot, _ = example
    assert {h.key: (h.cls, h.r, h.s) for h in hot} == {6: (BOTH_PROBE, 6, 4), 2: (PROBE_ONLY, 4, 1), 0: (BUILD_ONLY, 1, 4)}


GOLDEN = {  # strategy, form -> moved, busiest, merged for gateways 0, 1, 2
    ("hash_all", "complete"): (13.333, 43, (28, 4, 32)),
    ("stay_replicate", "printed"): (24, 39, (37, 40, 35)),
    ("stay_replicate", "complete"): (12, 26, (19, 22, 23)),
    ("four_route", "printed"): (14, 21, (17, 19, 20)),
    ("four_route", "complete"): (17.333, 26, (21, 19, 24)),
}


@pytest.mark.parametrize("name, form", GOLDEN)
def test_example_costs(example, name, form):
    _, _, profile = example
    moved, busiest, merged = GOLDEN[name, form]
    policy = POLICIES[name]
    assert round(cost.redistribution(profile, policy, form), 3) == moved
    assert round(cost.join_phase(profile, policy, form), 3) == busiest
    assert tuple(round(cost.merge_phase(profile, policy, g, form)) for g in range(3)) == merged


def test_example_exact_hash_volume(example):
    assert cost.redistribution(example[2], POLICIES["hash_all"], exact=True) == 12


def test_example_result(example):
    x, hot, _ = example
    for name in POLICIES:
        assert routed(x, hot, POLICIES[name], 3).count() == 35, name


def test_profile_of_equals_observed(example):
    x, hot, profile = example
    assert {v.hot.key: (v.r_at, v.s_at) for v in profile_of(x, hot, 3).loads} == {v.hot.key: (v.r_at, v.s_at) for v in profile.loads}


def test_choice_is_the_least_cost_with_ties_to_the_first(example):
    _, _, profile = example
    for g in (None, 0, 1, 2):
        for form in ("complete", "printed"):
            d = choose(profile, g, form)
            assert min(c[4] for c in d.costs) == next(c[4] for c in d.costs if c[0] == d.strategy)
    empty = choose(cost.Profile(3, ()))
    assert empty.strategy == "stay_replicate" and {c[4] for c in empty.costs} == {0.0}
    assert "hash_all" in choose(profile).explain()


def test_intro_leaves_a_node_idle(spark):
    """Staying rows of the hot key leave the node without them idle; scattering uses all nodes."""
    x = literal_sides(spark, intro())
    hot, _ = observe(x, 0.5, 3)
    stay = {r["dst"] for r in send(x.r, "probe", "a", hot, POLICIES["stay_replicate"], 3, x.r_hash).where("a = 3").select("dst").collect()}
    spread = {r["dst"] for r in send(x.r, "probe", "a", hot, POLICIES["scatter_replicate"], 3, x.r_hash).where("a = 3").select("dst").collect()}
    assert stay == {0, 1} and spread == {0, 1, 2}


def random_input(rng, n):
    keys = list(range(8))
    weights = [rng.random() ** 3 for _ in keys]
    make = lambda k: [(rng.choices(keys, weights)[0] if rng.random() > 0.05 else None, rng.randrange(n)) for _ in range(k)]
    r = make(rng.randrange(1, 60))
    rng.shuffle(weights)
    return r, make(rng.randrange(1, 40))


@pytest.mark.parametrize("seed", range(6))
def test_random_inputs_meet_once(spark, seed):
    rng = random.Random(seed)
    n = (1, 3, 4, 6, 12, 3)[seed]
    r, s = random_input(rng, n)
    x = sides(spark, r, s)
    hot, profile = observe(x, rng.choice([0.05, 0.1, 0.2]), n)
    want = expected(r, s)
    for name, policy in POLICIES.items():
        assert pairs(routed(x, hot, policy, n)) == want, name
        if n == 1:
            assert metrics.moved(x, hot, policy, 1).agg(F.sum("moved")).first()[0] == 0
        assert pairs(routed(x, hot, policy, n, fan={h.key: 1 + i % n for i, h in enumerate(hot) if "STAY" not in policy.of(h)})) == want, name
    assert pairs(branches(x, hot, POLICIES["four_route"], n)) == want
    assert pairs(branches(x, hot, POLICIES["scatter_replicate"], n, limit=0)) == want  # nothing may be broadcast
    assert pairs(routed(x, hot, choose_per_value(profile), n)) == want
    moved = metrics.moved(sides(spark, [v for v in r if v[0] in {h.key for h in hot}] or [(None, 0)], [v for v in s if v[0] in {h.key for h in hot}] or [(None, 0)]), hot, POLICIES["stay_replicate"], n)
    model = cost.redistribution(profile, POLICIES["stay_replicate"], exact=True)
    nulls = sum(1 for side in (r, s) if not any(v[0] in {h.key for h in hot} for v in side))
    got = moved.agg(F.sum("moved")).first()[0]
    assert model <= got <= model + nulls


@pytest.mark.parametrize("how", ["left", "right", "full", "left_semi", "left_anti"])
def test_other_join_types(spark, how):
    rng = random.Random(5)
    r, s = random_input(rng, 4)
    x = sides(spark, r, s)
    hot, _ = observe(x, 0.1, 4)
    plain = x.r.join(x.s, F.col("a") == F.col("b"), how)
    cols = ["rh", "a"] if "semi" in how or "anti" in how else ["rh", "a", "sh", "b"]
    for name in POLICIES:
        got = routed(x, hot, POLICIES[name], 4, how).select(cols)
        want = plain.select(cols)
        assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0, name


def test_residual_predicate_never_replicates_a_preserved_side(spark):
    rng = random.Random(9)
    r, s = random_input(rng, 4)
    x = sides(spark, r, s)
    hot, _ = observe(x, 0.1, 4)
    extra = (F.col("rh") + F.col("sh")) % 2 == 0
    cols = ["rh", "a", "sh", "b"]
    for how in ("inner", "left", "full"):
        want = x.r.join(x.s, (F.col("a") == F.col("b")) & extra, how).select(cols)
        got = routed(x, hot, POLICIES["scatter_replicate"], 4, how, extra).select(cols)
        assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0, how


def test_empty_sides_single_row_and_one_key(spark):
    for r, s in (([], [(1, 0)]), ([(1, 0)], []), ([], []), ([(1, 0)], [(1, 1)]), ([(7, i % 3) for i in range(9)], [(7, i % 3) for i in range(4)])):
        x = sides(spark, r, s)
        hot, _ = observe(x, 1.0, 3)
        assert pairs(routed(x, hot, POLICIES["four_route"], 3)) == expected(r, s)


def test_skew_join_plain_without_skew(spark):
    r, s = [(i, i % 3) for i in range(40)], [(i, i % 3) for i in range(40)]
    x = sides(spark, r, s)
    out = skew_join(x.r, x.s, "a", "b", p=0.2, n=3, placement=("src", "src"))
    assert pairs(out) == expected(r, s)


def test_composite_and_string_keys(spark):
    r = spark.createDataFrame([(i, f"k{i % 3 if i % 2 else 0}", 0) for i in range(30)], "rh long, a string, src int")
    s = spark.createDataFrame([(i, f"k{i % 2}", 0) for i in range(10)], "sh long, b string, src int")
    want = Counter((x["rh"], x["sh"]) for x in r.join(s, F.col("a") == F.col("b")).collect())
    for strategy in ("auto", "four_route", "stay_replicate", "hash_all"):
        assert pairs(skew_join(r, s, "a", "b", strategy, p=0.2, n=4)) == want
        assert pairs(skew_join(r, s, "a", "b", strategy, p=0.2, n=4, physical="routed")) == want


def test_partition_is_a_cover(example):
    x, hot, _ = example
    got = {(v["route"], v["a"]) for v in partition(x.r, "a", hot, "probe").select("route", "a").distinct().collect()}
    assert {(2, 2), (3, 6), (1, 0)} <= got
    with pytest.raises(ValueError):
        partition(x.r, "a", hot, "neither")


def test_fan_out_follows_the_work():
    hot = [HotKey(1, BOTH_PROBE, 900, 900), HotKey(2, BOTH_PROBE, 90, 90), HotKey(3, PROBE_ONLY, 500, 1)]
    fan = fan_out(hot, POLICIES["four_route"], 1000)
    assert fan[1] == 1000 and 10 < fan[2] < 30 and fan[3] == 1000
    assert fan_out([], POLICIES["four_route"], 10) == {}


def test_grid_shape_divides():
    for n in (1, 2, 3, 4, 6, 7, 12):
        a, c = grid_shape(n, 1000, 10)
        assert a * c == n
    assert grid_shape(12, 1000, 1000) in ((3, 4), (4, 3))
    assert grid_shape(12, 10**6, 1) == (12, 1)


def test_worst_node_bounds():
    assert cost.case_bound("own_node", "hash_all", 0, 30, 3, r_total=90) == 60
    assert cost.case_bound("own_node", "stay_replicate", 0, 30, 3, s_at=(5, 20, 5), r_total=90) == 50
    assert cost.case_bound("spread", "hash_all", 10, 4, 2) == 54
    assert cost.case_bound("spread", "four_route", 10, 4, 2, s_share=3) == 3 + 5 + 15


def test_bytes_weigh_the_sides(example):
    _, _, profile = example
    tuples = cost.redistribution(profile, POLICIES["hash_all"])
    assert abs(cost.in_bytes(profile, POLICIES["hash_all"], 1, 1) - tuples) < 1e-9
    assert cost.in_bytes(profile, POLICIES["hash_all"], 10, 1) > tuples


def test_cheaper_partial_spreads_what_sits_on_one_node():
    packed = cost.HotLoad(HotKey(1, PROBE_ONLY, 900, 10), 0, (900, 0, 0), (4, 3, 3))
    level = cost.HotLoad(HotKey(2, PROBE_ONLY, 900, 10), 0, (300, 300, 300), (4, 3, 3))
    special = cost.cheaper_partial(cost.Profile(3, (packed, level))).special
    assert special[1][0] == "SCATTER" and special[2][0] == "STAY"


def test_custom_policy(spark):
    r, s = [(7, i % 3) for i in range(9)] + [(1, 0)], [(7, 0)] * 3 + [(1, 1)]
    x = sides(spark, r, s)
    hot = classify.find(x.r, x.s, "a", "b", 0.3)
    mine = Policy("mine", {}, {7: (REPLICATE, "STAY")})
    assert mine.of(HotKey(5, "COLD", 1, 1)) == (HASH, HASH)
    assert pairs(routed(x, hot, mine, 3)) == expected(r, s)


def test_detectors_find_what_is_heavy(spark):
    rows = [(i % 10 if i % 2 else 3,) for i in range(2000)] + [(None,)] * 500
    df = spark.createDataFrame(rows, "k int").repartition(4)
    exact = {r["key"]: (r["cnt"], r["n_rows"]) for r in stats.exact_skew(df, "k", 0.1).collect()}
    assert exact[3][1] == 2000 and set(exact) >= {3}
    for found in (stats.sketch_skew(df, "k", 0.1), stats.top_k_skew(df, "k", 0.1), stats.runtime_skew(df, "k", 0.1, 10**6, verify=True), stats.sampled_skew(df, "k", 0.1, 0.5)):
        assert {r["key"]: (r["cnt"], r["n_rows"]) for r in found.collect()} == exact
    assert stats.analyze(df, "k").n_nulls == 500


def test_measures():
    assert metrics.faster_pct(1.0, 2.21) == pytest.approx(121)
    assert metrics.speedup({3: 10.0, 12: 35.0}) == {3: 1.0, 12: 3.5}
    assert metrics.stability([1.0, 1.0]) == 0 and metrics.regret("a", {"a": 3.0, "b": 2.0}) == 1.5
    assert metrics.throughput(10, 5, 3) == 5 and metrics.cold_volume(8, 4, 4) == 9


def test_semi_and_anti_read_every_row(spark, small):
    """Semi and anti join together hold each row of lineitem once."""
    from skewjoin.queries.join_queries import QUERIES

    rows = [r["n"] for how in ("semi", "anti") for r in QUERIES[f"{how}_four_route"](spark, small).collect()]
    assert sum(rows) == spark.read.parquet(f"{small}/lineitem.parquet").count()


# ---- the public join: partitions, join types, strategies, forms, names, types ----


def odd_inputs(spark, parts, seed=3):
    """Inputs whose columns bear the names the engine would like to use; strided keys, NULLs, repeated rows."""
    rng = random.Random(seed)
    key = lambda: rng.choice([8, 8, 8, 16, None, 8 * rng.randrange(40)])
    r = [(key(), rng.randrange(3), 99, "x", None) for _ in range(120)]
    s = [(key(), rng.randrange(2), 77, True) for _ in range(90)]
    return (
        spark.createDataFrame(r, "k long, src int, dst int, lead string, copied int").repartition(parts),
        spark.createDataFrame(s, "k int, src int, dst int, branch boolean").repartition(parts),
    )


def same(got, want):
    rows = lambda df: Counter(map(tuple, df.collect()))
    assert rows(got) == rows(want)


@pytest.mark.parametrize("parts", [1, 4, 13])
@pytest.mark.parametrize("how", ["inner", "left", "right", "full", "left_semi", "left_anti"])
def test_public_join_equals_the_plain_one(spark, parts, how):
    r, s = odd_inputs(spark, parts)
    want = r.join(s, r["k"] == s["k"], how)
    for strategy in ("auto", "hash_all", "stay_replicate", "four_route") if parts == 13 else ("scatter_replicate", "grid"):
        out = skew_join(r, s, "k", "k", strategy, p=0.1, n=4, how=how)
        assert out.columns == want.columns
        same(out, want)
    same(skew_join(r, s, "k", p=0.1, n=4, how=how, strategy="four_route"), r.join(s.withColumn("k", F.col("k").cast("long")), "k", how))
    if how == "inner":
        same(skew_join(r, s, "k", "k", "four_route", p=0.1, n=4, physical="branches"), want)
    if parts == 13:
        same(skew_join(r, s, "k", "k", "stay_replicate", p=0.1, n=4, how=how, placement=("dst", "dst")), want)


@pytest.mark.parametrize("how", ["inner", "full", "left_anti"])
def test_null_safe_and_composite_keys(spark, how):
    r, s = odd_inputs(spark, 5)
    r, s = r.withColumnsRenamed({"k": "a", "src": "i"}).drop("dst", "lead", "copied"), s.withColumnsRenamed({"k": "b", "src": "j"}).drop("dst", "branch")
    for a, b in ((["a"], ["b"]), (["a", "i"], ["b", "j"])):
        plain = [F.col(x) == F.col(y) for x, y in zip(a, b)]
        safe = [F.col(x).eqNullSafe(F.col(y)) for x, y in zip(a, b)]
        same(skew_join(r, s, a, b, "four_route", p=0.05, n=3, how=how), r.join(s, plain, how))
        same(skew_join(r, s, a, b, "stay_replicate", p=0.05, n=3, how=how, null_safe=True), r.join(s, safe, how))


def test_keys_of_other_types(spark):
    from datetime import date, datetime
    from decimal import Decimal

    values = {
        "string": ["a", "b"], "date": [date(2020, 1, 1), date(2021, 5, 5)], "timestamp": [datetime(2020, 1, 1, 3), datetime(2021, 1, 1, 0, 0, 0, 7)],
        "timestamp_ntz": [datetime(2020, 1, 1, 3), datetime(2021, 1, 1, 0, 0, 0, 7)], "decimal(12,3)": [Decimal("1.500"), Decimal("-2.250")],
        "double": [0.0, -0.0, float("nan")], "boolean": [True, False], "binary": [b"x", b"yz"],
    }
    for kind, keys in values.items():
        r = spark.createDataFrame([(keys[i % len(keys)], i) for i in range(30)], f"k {kind}, i int").repartition(7)
        s = spark.createDataFrame([(keys[(i * 7) % len(keys)], i) for i in range(20)], f"k {kind}, j int").repartition(6)
        hot, profile = observe(Sides(r, s, "k", "k"), 0.2, 3)
        assert len(hot) == len(set(map(str, keys))) - (kind == "double"), kind
        out = skew_join(r, s, "k", "k", "four_route", p=0.2, n=3, hot=hot).select("i", "j")
        same(out, r.join(s, r["k"] == s["k"]).select("i", "j"))
        routes = {v["k"] if not isinstance(v["k"], bytearray) else bytes(v["k"]): v["dst"] for v in routed(Sides(r.select("k"), s.select(F.col("k").alias("k2")), "k", "k2"), [], POLICIES["hash_all"], 3).select("k", "dst").collect()}
        assert all(routes[v.hot.key] == v.owner for v in profile.loads if v.hot.key == v.hot.key), kind
    with pytest.raises(ValueError):
        skew_join(spark.createDataFrame([(1,)], "k int"), spark.createDataFrame([("1",)], "k string"), "k", "k")
    with pytest.raises(ValueError):
        skew_join(spark.createDataFrame([(1, 2)], "k int, __skew_x int"), spark.createDataFrame([(1,)], "k int"), "k", "k", p=0.1)


def test_routing_is_even(spark):
    """Keys in steps are hashed over all nodes; equal rows of a hot key are spread; no column but the key is read."""
    strided = spark.range(8000).select((F.col("id") * 8).alias("k"))
    other = spark.range(8000).select((F.col("id") * 8).alias("j"))
    at = Counter(v["dst"] for v in routed(Sides(strided, other, "k", "j"), [], POLICIES["hash_all"], 8).select("dst").collect())
    assert len(at) == 8 and max(at.values()) < 1.3 * min(at.values())
    equal = spark.range(8000).select(F.lit(5).cast("long").alias("k"))
    few = spark.range(4).select(F.lit(5).cast("long").alias("j"))
    x = Sides(equal, few, "k", "j")
    hot, _ = observe(x, 0.1, 8)
    for name in ("scatter_replicate", "grid"):
        at = Counter(v["dst"] for v in routed(x, hot, POLICIES[name], 8).select("dst").collect())
        assert sum(at.values()) == 32000 and max(at.values()) < 1.3 * min(at.values()) and len(at) == 8, name


def test_only_needed_columns_are_read(spark, small):
    li, od = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("lineitem", "orders"))
    hot = [HotKey(1, BOTH_PROBE, 10, 10)]
    out = skew_join(li, od, "l_orderkey", "o_orderkey", "scatter_replicate", n=4, hot=hot).agg(F.count(F.lit(1)))
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_orderkey:bigint>" in plan and "l_extendedprice" not in plan and "o_totalprice" not in plan


def test_candidates_miss_no_heavy_value(spark):
    """A value exactly at the threshold, among very many light ones."""
    rows = spark.range(40_000).select(F.when(F.col("id") % 50 == 0, F.lit(-1)).when(F.col("id") % 50 == 1, F.lit(-2)).otherwise(F.col("id")).cast("long").alias("k")).repartition(9, "k")
    one = spark.range(1).select(F.lit(-9).cast("long").alias("j"))
    hot, _ = observe(Sides(rows, one, "k", "j"), 0.02, 4)
    assert {(h.key, h.r, h.s) for h in hot if h.cls == PROBE_ONLY} == {(-1, 800, 0), (-2, 800, 0)}
