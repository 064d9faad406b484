"""One routing engine for all strategies: a policy maps each class of key to what its two sides do."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce
from math import isqrt

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.keys import home_any
from ..plans.classify import BOTH_BUILD, BOTH_PROBE, BUILD_ONLY, COLD, PROBE_ONLY, HotKey

HASH, STAY, SCATTER, REPLICATE, GRID = "HASH", "STAY", "SCATTER", "REPLICATE", "GRID"


@dataclass(frozen=True)
class Policy:
    """class -> (probe action, build action); `special` overrides it for single keys."""

    name: str
    actions: dict[str, tuple[str, str]]
    special: dict = field(default_factory=dict)

    def of(self, hot: HotKey) -> tuple[str, str]:
        return self.special.get(hot.key, self.actions.get(hot.cls, (HASH, HASH)))


def _policy(name: str, probe_only, build_only, both_probe, both_build) -> Policy:
    return Policy(name, {COLD: (HASH, HASH), PROBE_ONLY: probe_only, BUILD_ONLY: build_only, BOTH_PROBE: both_probe, BOTH_BUILD: both_build})


_H, _G = (HASH, HASH), (GRID, GRID)
_KEEP_R, _KEEP_S = (STAY, REPLICATE), (REPLICATE, STAY)
_SPREAD_R, _SPREAD_S = (SCATTER, REPLICATE), (REPLICATE, SCATTER)

POLICIES = {
    p.name: p
    for p in (
        _policy("hash_all", _H, _H, _H, _H),
        _policy("stay_replicate", _KEEP_R, _KEEP_S, _KEEP_R, _KEEP_S),
        _policy("stay_replicate_grid", _KEEP_R, _KEEP_S, _G, _G),
        _policy("scatter_replicate", _SPREAD_R, _SPREAD_S, _SPREAD_R, _SPREAD_S),
        _policy("flow", _KEEP_R, _KEEP_S, _G, _G),
        _policy("grid", _G, _G, _G, _G),
        _policy("four_route", _KEEP_R, _H, _SPREAD_R, _SPREAD_S),
        _policy("four_route_scatter", _SPREAD_R, _H, _SPREAD_R, _SPREAD_S),
        _policy("subset_replicate", _KEEP_R, _H, _KEEP_R, _KEEP_R),
    )
}


def grid_shape(n: int, r: int = 1, s: int = 1) -> tuple[int, int]:
    """(rows, columns) with rows * columns = n that moves the fewest tuples: each probe row is copied
    once a column, each build row once a row."""
    shapes = [(d, n // d) for d in range(1, n + 1) if n % d == 0]
    return min(shapes, key=lambda x: (r * x[1] + s * x[0], abs(x[0] - isqrt(n))))


def member(key: Column, values: list, kind: T.DataType) -> Column:
    """Whether the key is one of the values: literals of the key's type; a struct is compared field by field."""
    if isinstance(kind, T.StructType):
        def same(value) -> Column:
            parts = [key.getField(f.name).eqNullSafe(_literal(v, f.dataType)) for f, v in zip(kind.fields, value)]
            return reduce(lambda x, y: x & y, parts)

        return reduce(lambda x, y: x | y, [same(v) for v in values])
    return key.isin(*[_literal(v, kind) for v in values])


def _literal(value, kind: T.DataType) -> Column:
    text = value is not None and isinstance(kind, T.TimestampNTZType)  # a naive datetime literal would be read in some zone
    return F.lit(str(value) if text else value).cast(kind)


def row_salt() -> Column:
    """A hash of a row's place: partition and number in it.

    Equal rows get different salts, and no column is read for it.  A retried task repeats it if
    its input comes in the same order, as from a scan; where that isn't so, name columns that
    tell rows apart and route by their hash.
    """
    return F.xxhash64(F.spark_partition_id(), F.monotonically_increasing_id())


def partition(df: DataFrame, key: str, hot: list[HotKey], side: str) -> DataFrame:
    """Add `route` 1..4: cold and build-only, probe-only, two-sided probe-heavy, two-sided build-heavy.

    The skewed values are at most 2/p literals, so this is a CASE in the scan's stage, no join.
    """
    if side not in ("probe", "build"):
        raise ValueError(side)
    route = F.lit(1)
    for number, cls in ((2, PROBE_ONLY), (3, BOTH_PROBE), (4, BOTH_BUILD)):
        keys = [h.key for h in hot if h.cls == cls]
        if keys:
            route = F.when(member(F.col(key), keys, df.schema[key].dataType), F.lit(number)).otherwise(route)
    return df.withColumn("route", route)


def _scatter(kind: str, row_hash: Column, n: int, seed: int) -> Column:
    if kind == "rowhash":
        return F.pmod(row_hash.cast("long"), F.lit(n).cast("long")).cast("int")
    if kind == "random":  # keyed, so that a retried task routes as before
        return F.pmod(F.xxhash64(F.lit(seed), row_hash), F.lit(n).cast("long")).cast("int")
    if kind == "round_robin":
        return F.pmod(F.monotonically_increasing_id(), F.lit(n).cast("long")).cast("int")
    raise ValueError(kind)


def fan_out(hot: list[HotKey], policy: Policy, n: int, slack: int = 2) -> dict:
    """key -> number of nodes it is spread over: its share of the skewed work, with some slack.

    Spreading every skewed value over all nodes copies its partner n times; with thousands of
    nodes a value needs only as many as its work fills.  A staying side lies anywhere, so its
    partner still goes everywhere.
    """
    work = {h.key: h.r + h.s + h.r * h.s for h in hot}
    whole = sum(work.values()) or 1
    return {
        h.key: n if STAY in policy.of(h) else max(1, min(n, -(-slack * n * work[h.key] // whole)))
        for h in hot
    }


def destinations(side: str, key: Column, kind: T.DataType, hot: list[HotKey], policy: Policy, n: int, row_hash: Column, owner: Column, src: Column, scatter: str = "rowhash", seed: int = 0, fan: dict | None = None) -> tuple[Column, bool]:
    """(where a row goes, whether that is an array): int, or array<int> if some rows have copies.

    A value spread over k < n nodes uses those from its owner on.  Whatever `src` says, rows stay
    on one of the n nodes.
    """
    at = 0 if side == "probe" else 1
    groups: dict[tuple, list] = {}
    for h in hot:
        action = policy.of(h)[at]
        if action != HASH:
            k = min(n, (fan or {}).get(h.key, n))
            shape = grid_shape(k, max(h.r, 1), max(h.s, 1)) if action == GRID else None
            groups.setdefault((action, shape, k), []).append(h.key)
    many = any(action in (REPLICATE, GRID) for action, _, _ in groups)
    wrap = (lambda c: F.array(c)) if many else (lambda c: c)
    out = wrap(owner)

    def nodes(first: Column | int, step: int, count: int, k: int) -> Column:
        """count nodes first, first + step, ..., counted from node 0 or, if k < n, from the owner."""
        if k == n and isinstance(first, int):
            return F.array(*[F.lit(first + i * step) for i in range(count)]) if n <= 64 else F.sequence(F.lit(first), F.lit(first + (count - 1) * step), F.lit(step))
        base = F.lit(first) if isinstance(first, int) else first
        if k < n:
            base = base + owner
        return F.transform(F.sequence(F.lit(0), F.lit(count - 1)), lambda i: F.pmod(base + i * step, F.lit(n)).cast("int"))

    for (action, shape, k), keys in groups.items():
        if action == STAY:
            to = wrap(F.pmod(src.cast("int"), F.lit(n)).cast("int"))
        elif action == SCATTER:
            to = _scatter(scatter, row_hash, k, seed)
            to = wrap(F.pmod(to + owner, F.lit(n)).cast("int") if k < n else to)
        elif action == REPLICATE:
            to = nodes(0, 1, k, k)
        else:
            rows, cols = shape
            h = row_hash.cast("long")
            if side == "probe":
                to = nodes(F.pmod(h, F.lit(rows).cast("long")).cast("int") * cols, 1, cols, k)
            else:
                to = nodes(F.pmod(h, F.lit(cols).cast("long")).cast("int"), cols, rows, k)
        out = F.when(member(key, keys, kind), to).otherwise(out)
    return out, many


def send(df: DataFrame, side: str, key: str, hot: list[HotKey], policy: Policy, n: int, row_hash: Column | None = None, scatter: str = "rowhash", seed: int = 0, owner: Column | None = None, fan: dict | None = None, src: Column | None = None, prefix: str = "", nulls: bool = True) -> DataFrame:
    """One row per copy with its destination `dst`; `copied` where the row is replicated, `lead` on its first copy.

    Rows with a NULL key match nothing: they are spread over the nodes (nulls=False: there are none).
    prefix: of the names of the added columns.
    """
    names = [prefix + c for c in ("dst", "copied", "lead", "to", "salt")]
    dst, copied, lead, to_, salt = names
    own = owner if owner is not None else home_any(F.col(key), n)
    spread = {policy.of(h)[0 if side == "probe" else 1] for h in hot} & {SCATTER, GRID}
    if spread or nulls:
        df = df.withColumn(salt, row_hash.cast("long") if row_hash is not None else row_salt())
    if nulls:
        own = F.when(F.col(key).isNull(), F.pmod(F.col(salt), F.lit(n).cast("long")).cast("int")).otherwise(own)
    to, many = destinations(side, F.col(key), df.schema[key].dataType, hot, policy, n, F.col(salt) if spread else F.lit(0), own, src if src is not None else F.col("src"), scatter, seed, fan)
    if not many:
        return df.withColumn(dst, to).withColumn(copied, F.lit(False)).withColumn(lead, F.lit(True)).drop(salt)
    df = df.withColumn(to_, to).drop(salt)
    return df.withColumn(copied, F.size(to_) > 1).withColumn(dst, F.explode(to_)).withColumn(lead, F.col(dst) == F.col(to_)[0]).drop(to_)
