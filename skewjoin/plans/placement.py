"""On which logical node a row lies before the join: column `src`, and profiles of it.

Logical nodes make the redistribution visible and countable; production joins work on
Spark's own partitions (mode `physical`).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.keys import home


def even(row_hash: Column, n: int) -> Column:
    return F.pmod(row_hash, F.lit(n).cast("long")).cast("int")


def by_key(key: Column, n: int) -> Column:
    return home(key, n)


def level(key: str, order: list[str], n: int) -> Column:
    """Each key's rows dealt one after the other: exactly even per key. For experiments: it sorts each key's rows."""
    return F.pmod(F.row_number().over(Window.partitionBy(key).orderBy(*order)), F.lit(n)).cast("int")


def hot_node(key: Column, row_hash: Column, n: int, keys: list, node: int, share: float) -> Column:
    """`share` of the rows of the given keys on one node, all else even."""
    on = key.isin(*keys) & (F.pmod(F.floor(row_hash / n), F.lit(100)) < int(share * 100))
    return F.when(on, F.lit(node)).otherwise(even(row_hash, n)).cast("int")


def range_replica(primary: Column, n: int, width: int, seed: int, stride: int = 5) -> Column:
    """A contiguous primary-key range has three replicas; the reader takes one of them, drawn by the seed."""
    rng = F.floor(primary / width).cast("long")
    draw = F.pmod(rng * 7919 + F.lit(seed * 104729), F.lit(1_000_003).cast("long"))
    choice = F.pmod(F.floor(draw / 7).cast("long"), F.lit(3).cast("long"))
    return F.pmod(rng * stride + choice, F.lit(n).cast("long")).cast("int")


def physical(n: int) -> Column:
    """Spark's own partition of a row, folded onto n nodes: an input may have any number of partitions."""
    return F.pmod(F.spark_partition_id(), F.lit(n)).cast("int")


def profile(df: DataFrame, key: str, hot_keys: DataFrame) -> DataFrame:
    """(src, key, cnt) of the skewed values: at most (number of values) x (number of nodes) rows."""
    rows = df.select("src", F.col(key).alias("key")).join(F.broadcast(hot_keys.select("key")), "key", "left_semi")
    return rows.groupBy("src", "key").agg(F.count(F.lit(1)).alias("cnt"))


def node_sizes(df: DataFrame) -> DataFrame:
    """(src, n): rows on each node, what a table reader would report."""
    return df.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
