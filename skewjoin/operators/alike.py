"""Joins of which only counts and sums are wanted: rows that are sent alike travel as one, with their number.

A hot key with m and n rows has m * n pairs, which no strategy can make at size, and need not if the
pairs are only counted and summed afterwards.  Each side is grouped by its key before it is sent; a
skewed key's rows also by the node that they lie on and by their hash modulo the number of nodes, which
are all that a strategy goes by.  So every group goes where its rows would go, and a pair of groups
stands for the product of their rows: any join type, strategy and form as before, at most keys * n^2
rows a side, and exact totals.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.classify import HotKey
from .dispatch import observe, profile_of, skew_join
from .routes import member, row_salt
from .strategies import Sides, _names, key_columns

ROWS_R, ROWS_S = "rows_of_r__", "rows_of_s__"
_SPREAD, _AT = {"probe": "spread_of_r__", "build": "spread_of_s__"}, {"probe": "at_of_r__", "build": "at_of_s__"}


def grouped(df: DataFrame, by: list[str], rows: str, sums=()) -> DataFrame:
    """One row for all that agree in `by`: their number as `rows`, and the sum of each column of `sums` under its name."""
    return df.groupBy(*by).agg(F.count(F.lit(1)).alias(rows), *[F.sum(c).alias(c) for c in sums])


def alike(x: Sides, hot: list[HotKey], n: int, r_sums=(), s_sums=(), r_also=(), s_also=()) -> Sides:
    """The sides with rows grouped that every strategy sends alike over n nodes.

    r_also, s_also: further columns that a residual predicate reads.  `hot` must have been found in
    the ungrouped rows, whose counts decide the routes.
    """
    keys = key_columns(x)

    def one(df: DataFrame, side: str, name, key: Column, row_hash: Column | None, rows: str, sums, also) -> DataFrame:
        kind = df.select(key.alias("k")).schema["k"].dataType
        special = member(key, [h.key for h in hot], kind) if hot else F.lit(False)
        spread = F.pmod(row_hash.cast("long") if row_hash is not None else row_salt(), F.lit(n).cast("long")).cast("int")
        df = df.withColumns({_SPREAD[side]: spread, _AT[side]: x.src(side, n)})  # before the grouping: a row's place is read here
        df = df.withColumns({c: F.when(special, F.col(c)).otherwise(0) for c in (_SPREAD[side], _AT[side])})
        return grouped(df, [*_names(name), _SPREAD[side], _AT[side], *also], rows, sums)

    return replace(
        x, r=one(x.r, "probe", x.a, keys[0], x.r_hash, ROWS_R, r_sums, r_also), s=one(x.s, "build", x.b, keys[1], x.s_hash, ROWS_S, s_sums, s_also),
        r_hash=F.col(_SPREAD["probe"]), s_hash=F.col(_SPREAD["build"]), r_src=_AT["probe"], s_src=_AT["build"],
    )


def pairs(how: str = "inner") -> Column:
    """The aggregate that counts a join's rows; a side that an outer join left out counts once."""
    if how in ("left_semi", "left_anti"):
        return F.sum(ROWS_R)
    return F.sum(F.coalesce(ROWS_R, F.lit(1)) * F.coalesce(ROWS_S, F.lit(1)))


def total(column: str, side: str, how: str = "inner") -> Column:
    """The aggregate that sums a column of `side`, 'r' or 's', over a join's rows."""
    if how in ("left_semi", "left_anti"):
        return F.sum(column)
    return F.sum(F.col(column) * F.coalesce(ROWS_S if side == "r" else ROWS_R, F.lit(1)))


def skew_join_alike(
    r: DataFrame, s: DataFrame, a: str | list[str], b: str | list[str] | None = None, r_sums=(), s_sums=(), strategy: str = "auto", p: float = 0.05, n: int | None = None,
    hot: list[HotKey] | None = None, profile=None, null_safe: bool = False, placement: tuple[str, str] | None = None, hash_columns: tuple[list[str], list[str]] | None = None, **options,
) -> DataFrame:
    """skew_join over groups of rows, for the aggregates `pairs` and `total`; skew is observed in the rows themselves."""
    n = n or int(r.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    row_hash = [F.xxhash64(*names) if names else None for names in hash_columns or (None, None)]
    src = placement or (None, None)
    x = Sides(r, s, a, a if b is None else b, row_hash[0], row_hash[1], src[0], src[1], null_safe)
    if hot is None:
        hot, profile = observe(x, p, n) if strategy != "hash_all" else ([], None)
    elif profile is None and strategy == "auto":
        profile = profile_of(x, hot, n)
    few = alike(x, hot, n, r_sums, s_sums)
    return skew_join(
        few.r, few.s, a, b, strategy, p, n, hot=hot, profile=profile, null_safe=null_safe, placement=(few.r_src, few.s_src),
        hash_columns=([_SPREAD["probe"]], [_SPREAD["build"]]), **options,
    )
