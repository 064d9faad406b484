"""Which key values are heavy: exactly, by sample, by sketch, or while the join is running.

A skewed value has at least p of the rows (more than p with strict=True), so there are at
most 1/p of them: what these functions return may be collected and broadcast whatever the
size of the table.  NULL keys never match and are left out, of the total as well.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil, log2

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def key_struct(keys: list[str]) -> Column:
    """One column for a key of several columns."""
    return F.col(keys[0]) if len(keys) == 1 else F.struct(*keys)


def _heavy(n: Column, total: Column, p: float, strict: bool) -> Column:
    bound = F.lit(p) * total
    # p * n is compared in doubles; a share that is exactly p must pass the inclusive test
    return n > bound + 1e-9 if strict else n >= bound - 1e-9


def exact_skew(df: DataFrame, key: str | Column, p: float, strict: bool = False) -> DataFrame:
    """(key, cnt, n_rows, share) of the skewed values, by one aggregation."""
    k = F.col(key) if isinstance(key, str) else key
    counts = df.select(k.alias("key")).where("key is not null").groupBy("key").agg(F.count(F.lit(1)).alias("cnt"))
    total = counts.agg(F.sum("cnt").alias("n_rows"))
    out = counts.crossJoin(F.broadcast(total))  # the total is one row
    return out.where(_heavy(F.col("cnt"), F.col("n_rows"), p, strict)).withColumn("share", F.col("cnt") / F.col("n_rows"))


def recount(df: DataFrame, key: str, candidates: DataFrame) -> DataFrame:
    """(key, cnt, n_rows): exact counts of a bounded set of candidate values."""
    rows = df.select(F.col(key).alias("key")).where("key is not null")
    total = rows.agg(F.count(F.lit(1)).alias("n_rows"))
    hit = rows.join(F.broadcast(candidates.select("key").distinct()), "key", "left_semi")
    return hit.groupBy("key").agg(F.count(F.lit(1)).alias("cnt")).crossJoin(F.broadcast(total))


def verified(df: DataFrame, key: str, candidates: DataFrame, p: float, strict: bool = False) -> DataFrame:
    """The skewed values among the candidates, with exact counts."""
    out = recount(df, key, candidates)
    return out.where(_heavy(F.col("cnt"), F.col("n_rows"), p, strict)).withColumn("share", F.col("cnt") / F.col("n_rows"))


def sampled_skew(df: DataFrame, key: str, p: float, fraction: float, seed: int = 1, margin: float = 0.3, verify: bool = True) -> DataFrame:
    """Candidates from a Bernoulli sample at p * (1 - margin), then counted exactly."""
    found = exact_skew(df.select(key).sample(False, fraction, seed), key, p * (1 - margin))
    if verify:
        return verified(df, key, found, p)
    return found.select("key", (F.col("cnt") / fraction).alias("cnt"), (F.col("n_rows") / fraction).alias("n_rows"), "share")


def sketch_skew(df: DataFrame, key: str, p: float, strict: bool = False) -> DataFrame:
    """Candidates from a mergeable frequent-items sketch, which misses no skewed value, then counted exactly.

    One scan with O(1/p) state for each task and no shuffle of the keys.
    """
    rows = df.select(F.col(key).alias("key")).where("key is not null")
    items = rows.freqItems(["key"], support=max(p / 2, 1e-4)).select(F.explode("key_freqItems").alias("key"))
    return verified(df, key, items, p, strict)


def hash_sampled_skew(df: DataFrame, key: str, p: float, row_hash: Column, one_in: int) -> DataFrame:
    """(key, cnt, n_rows, share) estimated from the rows whose hash is a multiple of `one_in`: the same sample in every run."""
    found = exact_skew(df.where(F.pmod(row_hash, F.lit(one_in)) == 0), key, p)
    return found.select("key", (F.col("cnt") * one_in).alias("cnt"), (F.col("n_rows") * one_in).alias("n_rows"), "share")


def frequent_hashes(column: str, p: float) -> str:
    """SQL of an aggregate: array of (item, count) with the hash of every value that has a share p of a group's rows.

    A mergeable frequent-items sketch that tracks 16/p items errs by 3.5 / (16/p) = 0.22 p of the
    rows at most, so a value with a share p is always reported; its count is never too low.
    """
    tracked = min(1 << ceil(log2(16 / p)), 1 << 19)
    return f"approx_top_k(xxhash64({column}), {min(tracked, 100_000)}, {tracked})"


def top_k_skew(df: DataFrame, key: str, p: float) -> DataFrame:
    """Candidates from the approximate top-k aggregate, then counted exactly."""
    k = ceil(1 / p)
    rows = df.select(F.col(key).alias("key")).where("key is not null")
    items = rows.agg(F.expr(f"approx_top_k(key, {k})").alias("t")).select(F.explode("t").alias("x")).select(F.col("x.item").alias("key"))
    return verified(df, key, items, p)


def runtime_skew(df: DataFrame, key: str, p: float, prefix_rows: int = 10_000, verify: bool = False) -> DataFrame:
    """(key, cnt, n_rows, share) estimated while scanning: a bounded counter over the first rows of each partition.

    The counter of a partition keeps 4 / p values (the smallest counts are decremented when
    it is full), so its state is bounded; counters merge by adding.
    """
    size = ceil(4 / p)

    def count(batches):
        held, seen, valid = None, 0, 0
        for batch in batches:
            values = batch.column(0).slice(0, max(0, prefix_rows - seen))
            seen += len(values)
            values = values.drop_null()
            valid += len(values)
            if len(values):
                new = values.value_counts()
                new = pa.table({"key": new.field(0), "cnt": new.field(1)})
                held = new if held is None else pa.concat_tables([held, new]).group_by("key").aggregate([("cnt", "sum")]).rename_columns(["key", "cnt"])
                if held.num_rows > size:  # decrement by the count of the first that must go
                    cut = pc.sort_indices(held.column("cnt"), sort_keys=[("", "descending")])[size]
                    least = held.column("cnt")[cut.as_py()]
                    held = held.set_column(1, "cnt", pc.subtract(held.column("cnt"), least)).filter(pc.greater(held.column("cnt"), least))
            if seen >= prefix_rows:
                break
        if valid:  # the number of rows goes with a row of its own, without a value
            keys, counts = held.column("key").combine_chunks(), held.column("cnt").combine_chunks()
            yield pa.RecordBatch.from_arrays(
                [pa.concat_arrays([pa.nulls(1, keys.type), keys]), pa.concat_arrays([pa.array([0], pa.int64()), counts]), pa.array([valid] + [0] * len(keys), pa.int64())],
                names=["key", "cnt", "seen"],
            )

    rows = df.select(F.col(key).alias("key"))
    parts = rows.mapInArrow(count, T.StructType([T.StructField("key", rows.schema["key"].dataType), T.StructField("cnt", T.LongType()), T.StructField("seen", T.LongType())]))
    total = parts.agg(F.sum("seen").alias("n_rows"))
    counts = parts.where("key is not null").groupBy("key").agg(F.sum("cnt").alias("cnt")).crossJoin(F.broadcast(total))
    found = counts.where(_heavy(F.col("cnt"), F.col("n_rows"), p, False)).withColumn("share", F.col("cnt") / F.col("n_rows"))
    return verified(df, key, found, p) if verify else found


def after_filter(df: DataFrame, key: str, known: DataFrame, predicate: str, p: float) -> DataFrame:
    """Skew of the rows that pass an atomic predicate, counting only what is known to be heavy before it.

    A filter that keeps the share f of the rows can make values heavy that had p * f before,
    so `known` should come from that lower threshold.
    """
    return verified(df.where(predicate), key, known, p)


def save_skew(skew: DataFrame, path: str, table: str, column: str, p: float) -> None:
    """Write a statistics sidecar; it holds at most 1/p rows."""
    tagged = skew.withColumns({"tbl": F.lit(table), "col": F.lit(column), "p": F.lit(p)})
    tagged.coalesce(1).write.mode("overwrite").parquet(path)


def load_skew(spark: SparkSession, path: str, table: str, column: str, p: float) -> DataFrame | None:
    """The sidecar's skew for a threshold of at least the one it was made with; None if it doesn't fit."""
    found = spark.read.parquet(path).where((F.col("tbl") == table) & (F.col("col") == column) & (F.col("p") <= p))
    if found.limit(1).count() == 0:
        return None
    return found.where(_heavy(F.col("cnt"), F.col("n_rows"), p, False)).select("key", "cnt", "n_rows", "share")


@dataclass(frozen=True)
class TableProfile:
    n_rows: int
    n_nulls: int
    n_distinct: int


def analyze(df: DataFrame, key: str) -> TableProfile:
    """Row, null and approximate distinct counts of a column in one scan."""
    row = df.agg(
        F.count(F.lit(1)).alias("n"), F.sum(F.col(key).isNull().cast("long")).alias("z"), F.approx_count_distinct(key).alias("d")
    ).first()
    return TableProfile(row["n"], row["z"] or 0, row["d"])
