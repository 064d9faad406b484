"""Joins to compare with: Spark's own, and those of the older literature on skew."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.catalog import text_bytes


def shuffled_hash(r: DataFrame, s: DataFrame, on: Column, how: str = "inner") -> DataFrame:
    """Parallel grace hash join: both sides dealt by key hash."""
    return r.join(s.hint("shuffle_hash"), on, how)


def sort_merge(r: DataFrame, s: DataFrame, on: Column, how: str = "inner") -> DataFrame:
    return r.join(s.hint("merge"), on, how)


def nested_loop(r: DataFrame, s: DataFrame, on: Column) -> DataFrame:
    """Any condition, |r| * |s| comparisons: only for conditions without an equality."""
    return r.join(s.hint("shuffle_replicate_nl"), on)


def broadcast_all(r: DataFrame, s: DataFrame, on: Column, how: str = "inner", limit: int = 256 << 20) -> DataFrame:
    """The build side copied to every task if its bytes, counted by a job, allow; else a shuffled hash join."""
    return r.join(F.broadcast(s), on, how) if text_bytes(s) <= limit else shuffled_hash(r, s, on, how)


def aqe_skew(r: DataFrame, s: DataFrame, on: Column) -> DataFrame:
    """Sort-merge join whose large reducer partitions Spark splits at run time, re-reading the partner for each
    split; it acts by bytes, after the map stage, under the session's settings (see `aqe_settings`)."""
    return r.join(s.hint("merge"), on)


@contextmanager
def aqe_settings(spark: SparkSession, threshold: str = "256MB", factor: float = 5.0):
    """Run actions with other thresholds of run-time splitting, and put the session's own back."""
    prefix = "spark.sql.adaptive."
    wanted = {
        "enabled": "true", "skewJoin.enabled": "true", "skewJoin.skewedPartitionThresholdInBytes": threshold, "skewJoin.skewedPartitionFactor": str(factor),
        "advisoryPartitionSizeInBytes": threshold,
    }
    before = {k: spark.conf.get(prefix + k, None) for k in wanted}
    try:
        for k, v in wanted.items():
            spark.conf.set(prefix + k, v)
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(prefix + k)
            else:
                spark.conf.set(prefix + k, v)


def salted(r: DataFrame, s: DataFrame, a: str, b: str, salts: int, row_hash: Column, keys: list | None = None) -> DataFrame:
    """Probe rows get one of `salts` salts, build rows all of them; only for the given keys if there are any."""
    hot = lambda c: F.lit(True) if keys is None else F.col(c).isin(*keys)
    left = r.withColumn("__salt", F.when(hot(a), F.pmod(row_hash, F.lit(salts)).cast("int")).otherwise(0))
    every = F.when(hot(b), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))
    right = s.withColumn("__copy", F.explode(every))
    return left.join(right, (F.col(a) == F.col(b)) & (F.col("__salt") == F.col("__copy"))).drop("__salt", "__copy")


def split_points(r: DataFrame, a: str, n: int, fraction: float = 1.0, seed: int = 1) -> list:
    """n - 1 quantiles of the key from a sample, merged as sketches: a bounded answer."""
    sample = r.select(a) if fraction >= 1 else r.select(a).sample(False, fraction, seed)
    cuts = [i / n for i in range(1, n)]
    return sample.agg(F.percentile_approx(a, cuts, 100_000).alias("q")).first()["q"] or []


def range_split(r: DataFrame, s: DataFrame, a: str, b: str, n: int, row_hash: Column, fraction: float = 1.0, rows: DataFrame | None = None) -> DataFrame:
    """Ranges of the key from a split vector.  A key that fills several ranges occurs several times in the
    vector: its probe rows are spread over those ranges and its build rows copied to all of them.  rows: those that
    r's rows stand for, if r has groups of them."""
    cuts = split_points(r if rows is None else rows, a, n, fraction)
    if not cuts:
        return r.join(s, F.col(a) == F.col(b))
    points = F.array(*[F.lit(c) for c in cuts])
    low = lambda key: F.size(F.filter(points, lambda c: c < F.col(key)))
    wide = lambda key: F.size(F.filter(points, lambda c: c == F.col(key)))
    left = r.withColumn("__at", (low(a) + F.pmod(row_hash, (wide(a) + 1).cast("long"))).cast("int"))
    right = s.withColumn("__to", F.explode(F.sequence(low(b), low(b) + wide(b))))
    left = left.repartitionById(n, F.col("__at"))
    right = right.repartitionById(n, F.col("__to"))
    return left.join(right.hint("shuffle_hash"), (F.col("__at") == F.col("__to")) & (F.col(a) == F.col(b))).drop("__at", "__to")


def lpt(weights: dict[int, int], n: int) -> dict[int, int]:
    """Longest processing time first: each bucket, heaviest first, to the least loaded node."""
    load, out = [0] * n, {}
    for bucket, w in sorted(weights.items(), key=lambda x: (-x[1], x[0])):
        at = min(range(n), key=lambda i: (load[i], i))
        out[bucket] = at
        load[at] += w
    return out


def multifit(weights: dict[int, int], n: int, steps: int = 20) -> dict[int, int]:
    """Bisect the capacity that first-fit-decreasing packing into n nodes needs."""
    order = sorted(weights.items(), key=lambda x: (-x[1], x[0]))
    whole, top = sum(weights.values()), max(weights.values(), default=0)

    def pack(capacity: float) -> dict[int, int] | None:
        load, out = [0] * n, {}
        for bucket, w in order:
            at = next((i for i in range(n) if load[i] + w <= capacity), None)
            if at is None:
                return None
            out[bucket] = at
            load[at] += w
        return out

    low, high = max(whole / n, top), max(2 * whole / n, top)
    best = pack(high) or lpt(weights, n)
    for _ in range(steps):
        middle = (low + high) / 2
        found = pack(middle)
        if found is None:
            low = middle
        else:
            best, high = found, middle
    return best


def _bucketed(r: DataFrame, s: DataFrame, a: str, b: str, n: int, buckets: int, plan, rows: tuple[str, str] | None = None) -> DataFrame:
    count = [F.count(F.lit(1)) if rows is None else F.sum(c) for c in rows or ("", "")]
    bucket = lambda key: F.pmod(F.col(key).cast("long") * 40503, F.lit(buckets)).cast("int")
    left, right = r.withColumn("__bucket", bucket(a)), s.withColumn("__bucket_s", bucket(b))
    weights = {x["__bucket"]: x["count"] for x in left.groupBy("__bucket").agg(count[0].alias("count")).collect() if x["__bucket"] is not None}
    for x in right.groupBy("__bucket_s").agg(count[1].alias("count")).collect():
        if x["__bucket_s"] is not None:
            weights[x["__bucket_s"]] = weights.get(x["__bucket_s"], 0) + x["count"]
    if not weights:
        return r.join(s, F.col(a) == F.col(b))
    owner = plan(weights, n)
    where = F.create_map(*[F.lit(v) for kv in owner.items() for v in kv])
    left = left.where(F.col(a).isNotNull()).withColumn("__node", F.coalesce(where[F.col("__bucket")], F.lit(0)).cast("int")).repartitionById(n, F.col("__node"))
    right = right.where(F.col(b).isNotNull()).withColumn("__node_s", F.coalesce(where[F.col("__bucket_s")], F.lit(0)).cast("int")).repartitionById(n, F.col("__node_s"))
    return left.join(right.hint("shuffle_hash"), (F.col("__node") == F.col("__node_s")) & (F.col(a) == F.col(b))).drop("__bucket", "__bucket_s", "__node", "__node_s")


def bucket_lpt(r: DataFrame, s: DataFrame, a: str, b: str, n: int, buckets: int = 256, rows: tuple[str, str] | None = None) -> DataFrame:
    """Hash buckets scheduled by size, longest first; only `buckets` counts reach the driver.

    rows: columns of r and s that say how many rows a row stands for; one each without them.
    """
    return _bucketed(r, s, a, b, n, buckets, lpt, rows)


def bucket_multifit(r: DataFrame, s: DataFrame, a: str, b: str, n: int, buckets: int = 256, rows: tuple[str, str] | None = None) -> DataFrame:
    return _bucketed(r, s, a, b, n, buckets, multifit, rows)
