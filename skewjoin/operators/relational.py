"""The relational surroundings of a join: thin, native compositions that Catalyst can plan freely."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def topk(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; ties are cut in the given order."""
    place = F.row_number().over(Window.partitionBy(*by).orderBy(*order))
    return df.withColumn("place", place).where(F.col("place") <= k)


def ranked(df: DataFrame, by: list[str], order: list[Column]) -> DataFrame:
    """row_number, rank, dense_rank and quartile of each row in its group."""
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumns({"rn": F.row_number().over(w), "rk": F.rank().over(w), "dr": F.dense_rank().over(w), "qt": F.ntile(4).over(w)})


def running(df: DataFrame, by: list[str], order: list[Column], value: str) -> DataFrame:
    """Running sum, previous and next value, and the sum of a frame of three rows."""
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumns({
        "run": F.sum(value).over(w.rowsBetween(Window.unboundedPreceding, 0)), "prev": F.lag(value).over(w), "next": F.lead(value).over(w),
        "three": F.sum(value).over(w.rowsBetween(-1, 1)),
    })


def asof(left: DataFrame, right: DataFrame, on: str, left_ts: str, right_ts: str, value: str, out: str) -> DataFrame:
    """Each left row with the last right value at or before its time: union, one sort per key, last value seen."""
    a = left.withColumns({"__t": F.col(left_ts), "__side": F.lit(1), "__v": F.lit(None).cast(right.schema[value].dataType)})
    b = right.select(F.col(on), F.col(right_ts).alias("__t"), F.lit(0).alias("__side"), F.col(value).alias("__v"))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(on).orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(out, F.last("__v", ignorenulls=True).over(w)).where("__side = 1").select(*left.columns, out)


def interval_join(left: DataFrame, right: DataFrame, on: str, left_ts: str, right_ts: str, seconds: int) -> DataFrame:
    """Pairs of equal key whose times are within `seconds`: an equi-join on key and time cell, right rows in two or three cells."""
    cell = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    a = left.withColumn("__cell", cell(F.col(left_ts)))
    b = right.withColumn("__cell", F.explode(F.sequence(cell(F.col(right_ts)) - 1, cell(F.col(right_ts)) + 1))).withColumnRenamed(on, "__on")
    micros = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    near = F.abs(micros(left_ts) - micros(right_ts)) <= seconds * 1_000_000
    return a.join(b, (F.col(on) == F.col("__on")) & (a["__cell"] == b["__cell"]) & near).drop("__cell", "__on")


def range_join(points: DataFrame, spans: DataFrame, value: str, low: str, high: str, step: int) -> DataFrame:
    """Points inside [low, high) of spans: spans are cut into cells of `step`, an equi-join does the rest."""
    p = points.withColumn("__cell", F.floor(F.col(value) / step))
    s = spans.withColumn("__cell", F.explode(F.sequence(F.floor(F.col(low) / step), F.floor((F.col(high) - 1) / step))))
    return p.join(s, "__cell").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("__cell")


def rollup(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.rollup(*keys).agg(*[c.alias(n) for n, c in aggs.items()])


def cube(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.cube(*keys).agg(*[c.alias(n) for n, c in aggs.items()])


def intersect_keys(a: DataFrame, b: DataFrame) -> DataFrame:
    """Keys heavy on both sides."""
    return a.select("key").intersect(b.select("key"))


def except_keys(a: DataFrame, b: DataFrame) -> DataFrame:
    """Keys heavy on the first side only."""
    return a.select("key").exceptAll(b.select("key"))


def bag_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows that one bag has more often than the other: empty if the bags are equal."""
    return a.exceptAll(b).withColumn("side", F.lit("first")).unionByName(b.exceptAll(a).withColumn("side", F.lit("second")))
