"""Choosing a strategy by cost, and the public join."""

from __future__ import annotations

from dataclasses import dataclass
from math import isnan, nan
from time import perf_counter

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans import classify, cost, stats
from ..plans.classify import HotKey
from .routes import HASH, POLICIES, REPLICATE, SCATTER, STAY, Policy, fan_out, member
from .strategies import R_KEY, R_SRC, RESERVED, S_KEY, S_SRC, Sides, branches_, keyed, routed_

#: Tried in this order; a later one must be strictly cheaper.
CANDIDATES = ("stay_replicate", "four_route", "hash_all")
#: The same with grids for two-sided values, as the experiments run stay-replicate.
CANDIDATES_GRID = ("stay_replicate_grid", "four_route", "hash_all")
#: The build side's key columns while both sides' are one.
USING = "__using_key_"


@dataclass(frozen=True)
class Decision:
    strategy: str
    costs: tuple[tuple[str, float, float, float, float], ...]  # name, redistribution, join, merge, total
    seconds: float
    n_hot: int

    def explain(self) -> str:
        rows = [f"{'strategy':<16}{'moved':>16}{'busiest':>16}{'merged':>16}{'total':>16}"]
        rows += [f"{n + (' *' if n == self.strategy else ''):<16}{a:>16.0f}{b:>16.0f}{c:>16.0f}{t:>16.0f}" for n, a, b, c, t in self.costs]
        return "\n".join(rows)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(*c, c[0] == self.strategy) for c in self.costs], "strategy string, moved double, busiest double, merged double, total double, chosen boolean")


def explain(decision: Decision) -> str:
    """All candidates' costs as text, the chosen one marked."""
    return decision.explain()


def _even(total: int, n: int) -> tuple[int, ...]:
    return tuple(total // n + (i < total % n) for i in range(n))


def profile_of(x: Sides, hot: list[HotKey], n: int) -> cost.Profile:
    """Tuples of known skewed values on each node, and their owners: one aggregation of both sides,
    at most 2/p * n rows collected.  Without placement columns the tuples count as spread evenly."""
    if not hot:
        return cost.Profile(n, ())
    r, s = keyed(x, n)
    kind = r.schema[R_KEY].dataType
    if not x.placed:
        return cost.Profile(n, tuple(cost.HotLoad(h, o, _even(h.r, n), _even(h.s, n)) for h, o in zip(hot, _owners(x, [h.key for h in hot], kind, n))))
    tagged = _tagged(r, s, x.placed).where(member(F.col("key"), [h.key for h in hot], kind))
    at = _counted(tagged, x, n)
    owners = _owners(x, [h.key for h in hot], kind, n)
    empty = [0] * n
    return cost.Profile(n, tuple(cost.HotLoad(h, o, tuple(at.get((True, h.key), empty)), tuple(at.get((False, h.key), empty))) for h, o in zip(hot, owners)))


def _owners(x: Sides, keys: list, kind, n: int) -> list[int]:
    """The node that each key is hashed to, by the very expression that routes it."""
    if not keys:
        return []
    spark = x.r.sparkSession
    rows = spark.createDataFrame([(i, k) for i, k in enumerate(keys)], T.StructType([T.StructField("i", T.IntegerType()), T.StructField("k", kind)]))
    return [r["o"] for r in sorted(rows.select("i", x.owner(F.col("k"), n).alias("o")).collect(), key=lambda r: r["i"])]


def _tagged(r: DataFrame, s: DataFrame, placed: bool) -> DataFrame:
    """(probe, key, src) of all rows of both sides with a key."""
    at = lambda c: F.col(c) if placed else F.lit(0)
    both = r.select(F.lit(True).alias("probe"), F.col(R_KEY).alias("key"), at(R_SRC).alias("src")).union(
        s.select(F.lit(False).alias("probe"), F.col(S_KEY).alias("key"), at(S_SRC).alias("src"))
    )
    return both.where("key is not null")


def _plain(key):
    """A collected key that can stand in a dictionary: one and the same NaN, as Spark has it."""
    if isinstance(key, float) and isnan(key):
        return nan
    return bytes(key) if isinstance(key, bytearray) else key


def _counted(tagged: DataFrame, x: Sides, n: int) -> dict:
    """(probe, key) -> tuples on each node."""
    out: dict = {}
    for row in tagged.groupBy("probe", "key", "src").agg(F.count(F.lit(1)).alias("cnt")).collect():
        at = out.setdefault((row["probe"], _plain(row["key"])), [0] * n)
        if x.placed:
            at[row["src"]] += row["cnt"]
        else:
            out[row["probe"], _plain(row["key"])] = list(_even(row["cnt"], n))
    return out


def observe(x: Sides, p: float, n: int, strict: bool = False, tie: str = "probe") -> tuple[list[HotKey], cost.Profile]:
    """Skewed values, their classes and their tuples on each node, exactly, from two scans of the keys.

    The first finds candidates of both sides by a mergeable frequent-items sketch of the keys'
    hashes, which misses no value with a share of p; the second counts the candidates' rows per
    node.  Neither shuffles keys: a task sends one sketch, then counts of at most 4/p values.
    Only skewed values' counts are collected, for at most n nodes of two sides.
    """
    r, s = keyed(x, n)
    kind = r.schema[R_KEY].dataType
    tagged = _tagged(r, s, x.placed)
    sketches = tagged.groupBy("probe").agg(F.expr(stats.frequent_hashes("key", p)).alias("top"), F.count(F.lit(1)).alias("t")).collect()
    total = {row["probe"]: row["t"] for row in sketches}
    codes = sorted({item["item"] for row in sketches for item in row["top"] if item["count"] >= p * row["t"] - 1e-9})
    if not codes:
        return [], cost.Profile(n, ())
    at = _counted(tagged.where(F.xxhash64("key").isin(*codes)), x, n)
    found = []
    for key in {k for _, k in at}:
        here = {side: at.get((side, key), [0] * n) for side in (True, False)}
        count = {side: sum(v) for side, v in here.items()}
        bound = {side: p * total.get(side, 0) for side in here}
        heavy = {side: count[side] > 0 and (count[side] > bound[side] + 1e-9 if strict else count[side] >= bound[side] - 1e-9) for side in here}
        if heavy[True] and heavy[False]:
            first = count[True] >= count[False] if tie == "probe" else count[True] > count[False]
            cls = classify.BOTH_PROBE if first else classify.BOTH_BUILD
        elif heavy[True] or heavy[False]:
            cls = classify.PROBE_ONLY if heavy[True] else classify.BUILD_ONLY
        else:
            continue
        found.append((HotKey(key, cls, count[True], count[False]), tuple(here[True]), tuple(here[False])))
    found.sort(key=lambda v: (-(v[0].r * v[0].s), -(v[0].r + v[0].s), str(v[0].key)))
    owners = _owners(x, [h.key for h, _, _ in found], kind, n)
    return [h for h, _, _ in found], cost.Profile(n, tuple(cost.HotLoad(h, o, r_at, s_at) for (h, r_at, s_at), o in zip(found, owners)))


def choose(profile: cost.Profile, gateway: int | None = None, form: str = "complete", candidates=CANDIDATES, weights=(1.0, 1.0, 1.0)) -> Decision:
    """The cheapest candidate; ties go to the earlier."""
    began = perf_counter()
    rows = []
    best = None
    for name in candidates:
        policy = POLICIES[name]
        parts = (cost.redistribution(profile, policy, form), cost.join_phase(profile, policy, form), cost.merge_phase(profile, policy, gateway, form))
        whole = sum(w * c for w, c in zip(weights, parts))
        rows.append((name, *parts, whole))
        if best is None or whole < best[1]:
            best = (name, whole)
    return Decision(best[0], tuple(rows), perf_counter() - began, len(profile.loads))


def choose_per_value(profile: cost.Profile, gateway: int | None = None) -> Policy:
    """Any mix of actions per skewed value, greedily by largest result: moved and merged tuples add up
    over values, the busiest node does not, so this is a heuristic."""
    actions = ((HASH, HASH), (STAY, REPLICATE), (REPLICATE, STAY), (SCATTER, REPLICATE), (REPLICATE, SCATTER))
    work = [0.0] * profile.n
    special: dict = {}
    for x in sorted(profile.loads, key=lambda x: -(x.r * x.s)):
        def price(action, x=x):
            parts = cost.shares(x, action, profile.n)
            busiest = max(w + cost.comp_node(r, s, r * s) for w, (r, s) in zip(work, parts))
            merged = 0.0 if gateway is None else sum(r * s for i, (r, s) in enumerate(parts) if i != gateway)
            return cost.net(x, action, profile.n) + busiest + merged
        picked = min(actions, key=price)
        if not (x.r and x.s):
            picked = (HASH, HASH)
        special[x.hot.key] = picked
        work = [w + cost.comp_node(r, s, r * s) for w, (r, s) in zip(work, cost.shares(x, picked, profile.n))]
    return Policy("per_value", POLICIES["hash_all"].actions, special)


def skew_join(
    r: DataFrame, s: DataFrame, a: str | list[str], b: str | list[str] | None = None, strategy: str = "auto", p: float = 0.05, n: int | None = None,
    how: str = "inner", residual: Column | None = None, gateway: int | None = None, hot: list[HotKey] | None = None, form: str = "complete",
    physical: str = "auto", profile: cost.Profile | None = None, null_safe: bool = False, placement: tuple[str, str] | None = None,
    hash_columns: tuple[list[str], list[str]] | None = None, candidates: tuple[str, ...] = CANDIDATES,
) -> DataFrame:
    """Join r and s on r.a = s.b with skewed keys treated apart: equal to the plain join as a bag of rows.

    a, b: a column of each side, or as many each; of equal or different names.  Without b the key
    columns `a` of both sides are one in the result, as in a join USING them.
    Without skew this is a plain join after the two scans that find none.  `hot` and `profile` take
    known statistics and save them; for other joins than inner ones `hot` must count these inputs.
    null_safe: NULL keys equal each other.  placement: columns of r and s that say on which node a
    row lies (folded onto n nodes); Spark's partitions without it.  hash_columns: columns of r and of
    s that tell rows apart, by which hot rows are spread; by a row's place without them, which a
    retried task repeats only if its input comes in the same order (see routes.row_salt).
    candidates: the strategies that 'auto' chooses among (CANDIDATES_GRID has grids for two-sided values).
    physical: 'routed' (and 'auto'), or 'branches', for inner joins without a residual predicate:
    it reads the inputs once for each class, and staying rows are not shuffled.
    """
    n = n or int(r.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    using = b is None
    if using:
        a = [a] if isinstance(a, str) else list(a)
        b = [f"{USING}{i}" for i in range(len(a))]
        s = s.withColumnsRenamed(dict(zip(a, b)))
    row_hash = [F.xxhash64(*names) if names else None for names in hash_columns or (None, None)]
    src = placement or (None, None)
    x = Sides(r, s, a, b, row_hash[0], row_hash[1], src[0], src[1], null_safe)
    if physical == "branches" and (how != "inner" or residual is not None):
        raise ValueError("the branch form is for inner joins without a residual predicate")
    if hot is None and strategy != "hash_all":
        hot, profile = observe(x, p, n)
    if not hot or strategy == "hash_all":
        left, right = keyed(x, n)
        on = F.col(R_KEY) == F.col(S_KEY)
        out = left.drop(R_SRC).join(right.drop(S_SRC), on if residual is None else on & residual, how).drop(R_KEY, S_KEY)
    else:
        if strategy == "auto":
            strategy = choose(profile_of(x, hot, n) if profile is None else profile, gateway, form, candidates).strategy
        policy = POLICIES[strategy]
        if physical == "branches":
            out = branches_(x, hot, policy, n).drop(RESERVED + "branch")
        else:
            out = routed_(x, hot, policy, n, how, residual, fan=fan_out(hot, policy, n)).drop(RESERVED + "dst")
    if not using or how in ("left_semi", "left_anti"):
        return out
    if how in ("right", "full"):
        out = out.withColumns({i: F.coalesce(i, j) for i, j in zip(a, b)})
    return out.drop(*b)


def sql_join(spark: SparkSession, left_sql: str, right_sql: str, a: str, b: str, **options) -> DataFrame:
    """skew_join over two SQL queries."""
    return skew_join(spark.sql(left_sql), spark.sql(right_sql), a, b, **options)
