"""Deterministic key and placement arithmetic, equal bit by bit in Spark and in any SQL engine.

All values are non-negative integers below MODULUS, from plain integer arithmetic on the
columns of a row, so that tests and retried tasks see the same rows everywhere.
"""

from __future__ import annotations

from bisect import bisect_right
from functools import lru_cache

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

MODULUS = 1_000_003

#: Multipliers of the columns that identify a row; the second set is independent of the first.
PROBE_TERMS = (("l_orderkey", 7919), ("l_partkey", 104729), ("l_suppkey", 1299709), ("l_linenumber", 15485863))
PROBE_PICK = (("l_orderkey", 15486719), ("l_partkey", 32452843), ("l_suppkey", 49979687), ("l_linenumber", 67867967))
BUILD_TERMS = (("o_orderkey", 7919), ("o_custkey", 104729))
BUILD_PICK = (("o_orderkey", 15486719), ("o_custkey", 32452843))


def mixed(terms) -> Column:
    """The sum of column * multiplier, modulo MODULUS."""
    total = None
    for name, factor in terms:
        part = F.col(name).cast("long") * F.lit(factor).cast("long")
        total = part if total is None else total + part
    return F.pmod(total, F.lit(MODULUS).cast("long"))


def mixed_sql(terms) -> str:
    return "((" + " + ".join(f"{name}::BIGINT * {factor}" for name, factor in terms) + f") % {MODULUS})"


def home(key: Column, n: int) -> Column:
    """Hash owner of an integer key in the worked examples and experiments: (key + 1) mod n, as INT.

    Not for production: keys in regular steps fall on few nodes.
    """
    return F.pmod(key.cast("long") + 1, F.lit(n).cast("long")).cast("int")


def md5_bucket(text: Column, n: int) -> Column:
    """A string's bucket by the first eight hexadecimal digits of its md5, the same in any SQL engine."""
    return F.pmod(F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(n).cast("long"))


def home_any(key: Column, n: int) -> Column:
    """Hash owner of a key of any hashable type."""
    return F.pmod(F.xxhash64(key), F.lit(n).cast("long")).cast("int")


@lru_cache(maxsize=64)
def zipf_bounds(z: float, n_values: int) -> tuple[int, ...]:
    """Upper bounds of the slices of [0, MODULUS) that the ranks 1..n_values get."""
    weights = [k ** -z for k in range(1, n_values + 1)]
    total, run, out = sum(weights), 0.0, []
    for w in weights:
        run += w
        out.append(min(MODULUS, int(MODULUS * run / total)))
    out[-1] = MODULUS
    return tuple(out)


def zipf_rank(u: int, z: float, n_values: int) -> int:
    return bisect_right(zipf_bounds(z, n_values), u) + 1


def assign_zipf(df: DataFrame, u: str, z: float, n_values: int, out: str) -> DataFrame:
    """Add column `out`: the rank whose slice holds df[u].

    A range join made an equi-join: slices are cut at multiples of STEP, so a row looks
    only at the slices of its own cell.  The table has n_values + MODULUS / STEP rows at
    most, which bounds the broadcast.
    """
    step = 1000
    rows, low = [], 0
    for rank, high in enumerate(zipf_bounds(z, n_values), 1):
        while low < high:
            upto = min(high, (low // step + 1) * step)
            rows.append((low // step, low, upto, rank))
            low = upto
    table = df.sparkSession.createDataFrame(rows, "zipf_cell int, zipf_low int, zipf_high int, zipf_rank long")
    cell = F.floor(F.col(u) / step).cast("int")
    return (
        df.join(F.broadcast(table), (cell == F.col("zipf_cell")) & (F.col(u) >= F.col("zipf_low")) & (F.col(u) < F.col("zipf_high")))
        .withColumn(out, F.col("zipf_rank")).drop("zipf_cell", "zipf_low", "zipf_high", "zipf_rank")
    )


def zipf_sql(z: float, n_values: int) -> str:
    """A SQL relation (rank, low, high) of the slices."""
    bounds = ", ".join(map(str, zipf_bounds(z, n_values)))
    return f"(SELECT i AS rank, coalesce(bs[i - 1], 0) AS low, bs[i] AS high FROM (SELECT [{bounds}] AS bs) t, range(1, {n_values + 1}) k(i))"


def single_key(u: Column, share: float, key: int = 7) -> Column:
    """One hot key with the given share of the rows, all other keys cold."""
    return F.when(u < int(share * MODULUS), F.lit(key).cast("long")).otherwise(u + 1000)


def single_sql(u: str, share: float, key: int = 7) -> str:
    return f"(CASE WHEN {u} < {int(share * MODULUS)} THEN {key} ELSE 1000 + {u} END)"


class ZipfRows:
    """Python table function: (row, rank) of each given row number at exponent z, drawn by the same arithmetic."""

    @staticmethod
    def register(spark: SparkSession, name: str = "zipf_rows") -> None:
        @F.udtf(returnType="row long, rank long")
        class Rows:
            def __init__(self):
                self.held = {}

            def bounds(self, z: float, n_values: int) -> list:
                if (z, n_values) not in self.held:
                    weights = [k ** -float(z) for k in range(1, n_values + 1)]
                    total, whole, out = 0.0, sum(weights), []
                    for w in weights:
                        total += w
                        out.append(total / whole)
                    self.held[z, n_values] = out
                return self.held[z, n_values]

            def eval(self, row: int, z: float, n_values: int):
                if row is not None:
                    x = (row * 7919 + 104729) % 1000003 / 1000003
                    yield row, min(bisect_right(self.bounds(z, n_values), x) + 1, n_values)

        spark.udtf.register(name, Rows)
