"""The join strategies, in two physical forms with one meaning.

Routed form: every row carries its destination node, both sides are dealt once by it, and
one equi-join on (destination, key) does all local joins: classes are disjoint in the key,
so a pair meets at exactly one node.  Everything the cost model speaks of can be counted.

Branch form, for production: one join per class, united.  Keeping rows where they are is no
exchange at all (the partner's slice is broadcast), scattering is a round-robin exchange.
A slice is broadcast only if its counted bytes stay under a bound; beyond it the class goes
through the routed form as a grid, whose copies per row grow with the root of n.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce
from typing import Protocol

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.keys import home, home_any
from ..plans import classify, cost, placement, stats
from ..plans.classify import BOTH_BUILD, BOTH_PROBE, BUILD_ONLY, PROBE_ONLY, HotKey
from ..sources.catalog import text_bytes
from .routes import GRID, POLICIES, REPLICATE, SCATTER, STAY, Policy, member, send

#: Bytes of a slice that may be broadcast in the branch form, as counted; checked before every broadcast.
BROADCAST_BYTES = 256 << 20
OUTER = {"left", "right", "full"}
#: Names that the engine adds to the inputs start so; none of theirs may.
RESERVED = "__skew_"
R_KEY, S_KEY, R_SRC, S_SRC = (RESERVED + c for c in ("r_key", "s_key", "r_src", "s_src"))


@dataclass(frozen=True)
class Sides:
    """A join's two inputs and what is known of their rows.

    a, b: the key columns, a name or as many names each.  r_hash, s_hash: hashes that tell
    rows apart, by which they are spread; without one a row's place is hashed.  r_src, s_src:
    columns that say on which node a row lies; without one its Spark partition says so.
    null_safe: NULL equals NULL.  home: the owner of a key, 'hash' or, in the worked examples,
    'example' (integer keys only).
    """

    r: DataFrame
    s: DataFrame
    a: str | list[str] = "a"
    b: str | list[str] = "b"
    r_hash: Column | None = None
    s_hash: Column | None = None
    r_src: str | None = None
    s_src: str | None = None
    null_safe: bool = False
    home: str = "hash"

    def owner(self, key: Column, n: int) -> Column:
        return home(key, n) if self.home == "example" else home_any(key, n)

    def src(self, side: str, n: int) -> Column:
        name = self.r_src if side == "probe" else self.s_src
        return placement.physical(n) if name is None else F.pmod(F.col(name).cast("int"), F.lit(n)).cast("int")

    @property
    def placed(self) -> bool:
        return self.r_src is not None and self.s_src is not None


def _names(x: str | list[str]) -> list[str]:
    return [x] if isinstance(x, str) else list(x)


def _column(df: DataFrame, name: str):
    """The field of a column, found by name as Spark does."""
    return df.select(F.col(name)).schema[0].dataType


def key_columns(x: Sides) -> tuple[Column, Column]:
    """The keys of both sides as one column each, of equal types, NULL where the key matches nothing.

    Types that differ are cast as a comparison would; -0.0 becomes 0.0.  A key of several
    columns is a struct, and so is a null-safe one, since a struct of NULLs equals its like.
    """
    a, b = _names(x.a), _names(x.b)
    if len(a) != len(b) or not a:
        raise ValueError("both sides need the same number of key columns")
    parts: tuple[list, list] = ([], [])
    for i, j in zip(a, b):
        kinds = _column(x.r, i), _column(x.s, j)
        kind = kinds[0]
        if kinds[0] != kinds[1]:
            texts = [isinstance(k, (T.StringType, T.BinaryType)) for k in kinds]
            if texts[0] != texts[1]:
                raise ValueError(f"cast one of the keys {i} ({kinds[0].simpleString()}) and {j} ({kinds[1].simpleString()})")
            one = x.r.sparkSession.range(0).select(F.coalesce(F.lit(None).cast(kinds[0]), F.lit(None).cast(kinds[1])).alias("k"))
            kind = one.schema["k"].dataType
        for part, name, own in ((parts[0], i, kinds[0]), (parts[1], j, kinds[1])):
            c = F.col(name) if own == kind else F.col(name).cast(kind)
            part.append(c + F.lit(0).cast(kind) if isinstance(kind, (T.FloatType, T.DoubleType)) else c)
    out = []
    for part in parts:
        if len(part) == 1 and not x.null_safe:
            out.append(part[0])
            continue
        fields = F.struct(*[c.alias(f"k{i}") for i, c in enumerate(part)])
        filled = reduce(lambda p, q: p & q, [c.isNotNull() for c in part])
        out.append(fields if x.null_safe else F.when(filled, fields))
    return out[0], out[1]


def keyed(x: Sides, n: int) -> tuple[DataFrame, DataFrame]:
    """Both inputs with their key and node in columns of reserved names."""
    for df in (x.r, x.s):
        taken = [c for c in df.columns if c.startswith(RESERVED)]
        if taken:
            raise ValueError(f"reserved names: {taken}")
    rk, sk = key_columns(x)
    return (
        x.r.withColumns({R_KEY: rk, R_SRC: x.src("probe", n)}),
        x.s.withColumns({S_KEY: sk, S_SRC: x.src("build", n)}),
    )


def _preserved_copied(policy: Policy, hot: list[HotKey], how: str) -> bool:
    """Whether a side whose unmatched rows the join keeps is replicated for some key."""
    pairs = [policy.of(h) for h in hot]
    probe = any(p in (REPLICATE, GRID) for p, _ in pairs)
    build = any(q in (REPLICATE, GRID) for _, q in pairs)
    return (probe and how in ("left", "full", "left_semi", "left_anti")) or (build and how in ("right", "full"))


def safe_policy(policy: Policy, hot: list[HotKey], how: str, residual: bool) -> Policy:
    """With a residual predicate a replicated row may have no match at all; then a side that the
    join preserves must not be replicated, and such keys are hashed."""
    if not residual or not _preserved_copied(policy, hot, how):
        return policy
    return POLICIES["hash_all"]


def routed(x: Sides, hot: list[HotKey], policy: Policy, n: int, how: str = "inner", residual: Column | None = None, scatter: str = "rowhash", fan: dict | None = None) -> DataFrame:
    """The join in routed form: the columns of both sides as they are, and the node `dst` that made the row.

    `fan` limits the nodes that a key is spread over (see routes.fan_out); all n without it.

    Replicated rows are copied only for values that the other side has, so every one of them
    has a match somewhere: its null-extended copies at other nodes are dropped.  Semi joins
    keep single rows of copied keys by their first copy.  Other joins than inner ones need
    counts of these very inputs in `hot`.
    """
    return routed_(x, hot, policy, n, how, residual, scatter, fan).withColumnRenamed(RESERVED + "dst", "dst")


def routed_(x: Sides, hot: list[HotKey], policy: Policy, n: int, how: str, residual: Column | None, scatter: str = "rowhash", fan: dict | None = None) -> DataFrame:
    """routed, with the node in a column of a reserved name."""
    policy = safe_policy(policy, hot, how, residual is not None)
    hot = [h for h in hot if h.r and h.s] if how != "inner" else hot  # a value without partners is not copied
    r, s = keyed(x, n)
    keep_r, keep_s = how in ("left", "full", "left_anti"), how in ("right", "full")
    r, s = r if keep_r else r.where(F.col(R_KEY).isNotNull()), s if keep_s else s.where(F.col(S_KEY).isNotNull())
    r_, s_ = RESERVED + "r_", RESERVED + "s_"
    r = send(r, "probe", R_KEY, hot, policy, n, x.r_hash, scatter, owner=x.owner(F.col(R_KEY), n), fan=fan, src=F.col(R_SRC), prefix=r_, nulls=keep_r)
    s = send(s, "build", S_KEY, hot, policy, n, x.s_hash, scatter, owner=x.owner(F.col(S_KEY), n), fan=fan, src=F.col(S_SRC), prefix=s_, nulls=keep_s)
    r, s = r.drop(R_SRC).repartitionById(n, F.col(r_ + "dst")), s.drop(S_SRC).repartitionById(n, F.col(s_ + "dst"))
    on = (F.col(r_ + "dst") == F.col(s_ + "dst")) & (F.col(R_KEY) == F.col(S_KEY))
    if residual is not None:
        on = on & residual
    if how in ("left_semi", "left_anti"):
        # rows of copied probe keys all match: they are kept once (semi) or dropped (anti) without a join
        out = r.where(~F.col(r_ + "copied")).join(s, on, how)
        if how == "left_semi":
            out = out.unionByName(r.where(F.col(r_ + "copied") & F.col(r_ + "lead"))) if len(set(r.columns)) == len(r.columns) else out.union(r.where(F.col(r_ + "copied") & F.col(r_ + "lead")))
        return out.withColumnRenamed(r_ + "dst", RESERVED + "dst").drop(R_KEY, r_ + "copied", r_ + "lead")
    joined = r.join(s.hint("shuffle_hash") if how in ("inner", "left") else s, on, how)
    if how in OUTER:
        false_r = F.col(s_ + "dst").isNull() & F.col(r_ + "copied")
        false_s = F.col(r_ + "dst").isNull() & F.col(s_ + "copied")
        joined = joined.where(~F.coalesce(false_r, F.lit(False)) & ~F.coalesce(false_s, F.lit(False)))
    joined = joined.withColumn(RESERVED + "dst", F.coalesce(r_ + "dst", s_ + "dst"))
    return joined.drop(R_KEY, S_KEY, *[p + c for p in (r_, s_) for c in ("dst", "copied", "lead")])


def branches(x: Sides, hot: list[HotKey], policy: Policy, n: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """The inner join in branch form, each row labelled with its `branch`.

    A slice is broadcast if its bytes, counted by a job, stay under `limit`.
    """
    return branches_(x, hot, policy, n, limit).withColumnRenamed(RESERVED + "branch", "branch")


def branches_(x: Sides, hot: list[HotKey], policy: Policy, n: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """branches, with the label in a column of a reserved name."""
    r, s = keyed(x, n)
    r, s = r.drop(R_SRC).where(F.col(R_KEY).isNotNull()), s.drop(S_SRC).where(F.col(S_KEY).isNotNull())
    kind = r.schema[R_KEY].dataType
    some = lambda df, key, values: df.where(member(F.col(key), values, kind))
    rest = lambda df, key, values: df.where(~member(F.col(key), values, kind)) if values else df
    special = [h.key for h in hot if policy.of(h) != ("HASH", "HASH")]
    on = F.col(R_KEY) == F.col(S_KEY)
    label = lambda df, name: df.drop(R_KEY, S_KEY).withColumn(RESERVED + "branch", F.lit(name))
    out = label(rest(r, R_KEY, special).join(rest(s, S_KEY, special), on), "hash")
    groups: dict[tuple[str, str], list[HotKey]] = {}
    for h in hot:
        if h.key in special:
            groups.setdefault(policy.of(h), []).append(h)
    for (probe, build), keys in groups.items():
        values = [h.key for h in keys]
        r_part, s_part = some(r, R_KEY, values), some(s, S_KEY, values)
        if probe != GRID and build == REPLICATE and text_bytes(s_part) <= limit:
            moved = r_part if probe == STAY else r_part.repartition(n)
            out = out.union(label(moved.join(F.broadcast(s_part), on), f"{probe.lower()}-probe"))
        elif probe == REPLICATE and text_bytes(r_part) <= limit:
            moved = s_part if build == STAY else s_part.repartition(n)
            # the probe side's columns first: an inner join with the left side broadcast
            out = out.union(label(F.broadcast(r_part).join(moved, on), f"{build.lower()}-build"))
        else:  # a grid, or too much to broadcast
            out = out.union(_grid(x, keys, n, kind).withColumn(RESERVED + "branch", F.lit("grid")))
    return out


def _grid(x: Sides, keys: list[HotKey], n: int, kind: T.DataType) -> DataFrame:
    values = [h.key for h in keys]
    rk, sk = key_columns(x)
    return routed_(replace(x, r=x.r.where(member(rk, values, kind)), s=x.s.where(member(sk, values, kind))), keys, POLICIES["grid"], n, "inner", None).drop(RESERVED + "dst")


def grid_join(x: Sides, keys: list[HotKey], n: int) -> DataFrame:
    """Keys of any weight on either side over a grid of n cells, by shuffle alone."""
    return _grid(x, keys, n, x.r.select(key_columns(x)[0].alias("k")).schema["k"].dataType)


class SubOperator(Protocol):
    """What the dispatcher asks of a strategy: its three costs, and the join itself."""

    name: str

    def net_cost(self, profile: cost.Profile) -> float: ...

    def comp_cost(self, profile: cost.Profile) -> float: ...

    def merge_cost(self, profile: cost.Profile, gateway: int) -> float: ...

    def execute(self, x: Sides, hot: list[HotKey], n: int, how: str) -> DataFrame: ...


@dataclass(frozen=True)
class Strategy:
    """A policy with its cost model; implements SubOperator."""

    policy: Policy
    form: str = "complete"

    @property
    def name(self) -> str:
        return self.policy.name

    def net_cost(self, profile: cost.Profile) -> float:
        return cost.redistribution(profile, self.policy, self.form)

    def comp_cost(self, profile: cost.Profile) -> float:
        return cost.join_phase(profile, self.policy, self.form)

    def merge_cost(self, profile: cost.Profile, gateway: int) -> float:
        return cost.merge_phase(profile, self.policy, gateway, self.form)

    def execute(self, x: Sides, hot: list[HotKey], n: int, how: str = "inner") -> DataFrame:
        return routed(x, hot, self.policy, n, how)


def hash_all(x: Sides, n: int, **kw) -> DataFrame:
    return routed(x, [], POLICIES["hash_all"], n, **kw)


def stay_replicate(x: Sides, hot: list[HotKey], n: int, both: str = "one_side", **kw) -> DataFrame:
    return routed(x, hot, POLICIES["stay_replicate" if both == "one_side" else "stay_replicate_grid"], n, **kw)


def scatter_replicate(x: Sides, hot: list[HotKey], n: int, **kw) -> DataFrame:
    return routed(x, hot, POLICIES["scatter_replicate"], n, **kw)


def grid(x: Sides, hot: list[HotKey], n: int, **kw) -> DataFrame:
    return routed(x, hot, POLICIES["grid"], n, **kw)


def subset_replicate(x: Sides, hot: list[HotKey], n: int, **kw) -> DataFrame:
    return routed(x, hot, POLICIES["subset_replicate"], n, **kw)


def four_route(x: Sides, hot: list[HotKey], n: int, partial: str = "stay", profile: cost.Profile | None = None, **kw) -> DataFrame:
    """partial: what probe-only keys do: 'stay', 'scatter', or 'auto', the cheaper per key by `profile`."""
    policy = POLICIES["four_route_scatter" if partial == "scatter" else "four_route"]
    if partial == "auto":
        if profile is None:
            raise ValueError("auto needs a placement profile")
        policy = cost.cheaper_partial(profile)
    return routed(x, hot, policy, n, **kw)


def four_route_branches(x: Sides, hot: list[HotKey], n: int, **kw) -> DataFrame:
    return branches(x, hot, POLICIES["four_route"], n, **kw)


def flow_hot(x: Sides, n: int, p: float, detect: str = "runtime", prefix_rows: int = 10_000) -> list[HotKey]:
    """The skewed values that flow joins by: candidates from a job over prefixes, or statistics, counted exactly."""
    if detect == "runtime":
        def detector(df, key, share):
            return stats.runtime_skew(df, key, share, prefix_rows, verify=True)
    else:
        detector = None
    r, s = keyed(x, n)
    return classify.find(r, s, R_KEY, S_KEY, p, detect=detector)


def flow(x: Sides, n: int, p: float, detect: str = "runtime", use_grid: bool = True, prefix_rows: int = 10_000, **kw) -> DataFrame:
    """Detection first (a job over prefixes, or statistics), then the join with grids for two-sided keys.

    Estimated counts choose the routes only; candidates are recounted before classifying, since a
    replicated value must really occur on the other side.
    """
    hot = flow_hot(x, n, p, detect, prefix_rows)
    return routed(x, hot, POLICIES["flow" if use_grid else "stay_replicate"], n, **kw)


__all__ = [
    "Sides", "Strategy", "SubOperator", "routed", "branches", "hash_all", "stay_replicate", "scatter_replicate", "grid",
    "subset_replicate", "four_route", "four_route_branches", "flow", "flow_hot", "grid_join", "safe_policy",
    "PROBE_ONLY", "BUILD_ONLY", "BOTH_PROBE", "BOTH_BUILD", "SCATTER",
]
