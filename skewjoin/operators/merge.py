"""How a query ends: rows gathered at one node, or results kept where they are."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def gather(df: DataFrame, n: int, gateway: int) -> DataFrame:
    """All rows in the partition of the gateway node, for a client that wants rows."""
    return df.repartitionById(n, F.lit(gateway))


def gather_others(joined: DataFrame, n: int, gateway: int) -> DataFrame:
    """Rows made at the gateway (`dst`) where they are, all others sent to it: what a merge moves.

    Both halves filter on the destination below their joins, so no pair is made twice.
    """
    own = joined.where(F.col("dst") == gateway)
    return own.union(joined.where(F.col("dst") != gateway).repartitionById(n, F.lit(gateway)))


def keep_local(df: DataFrame) -> DataFrame:
    """Results stay; what follows is a partial aggregation in place."""
    return df


def count_through(r: DataFrame, s: DataFrame, a: str, b: str) -> DataFrame:
    """(key, pairs): the size of the join per key from two small aggregates, without making a pair."""
    left = r.where(F.col(a).isNotNull()).groupBy(F.col(a).alias("key")).agg(F.count(F.lit(1)).alias("r_n"))
    right = s.where(F.col(b).isNotNull()).groupBy(F.col(b).alias("key")).agg(F.count(F.lit(1)).alias("s_n"))
    return left.join(right, "key").select("key", (F.col("r_n") * F.col("s_n")).alias("pairs"))
