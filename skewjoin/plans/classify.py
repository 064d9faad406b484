"""Key values by the side on which they are heavy."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

COLD, PROBE_ONLY, BUILD_ONLY, BOTH_PROBE, BOTH_BUILD = "COLD", "PROBE_ONLY", "BUILD_ONLY", "BOTH_PROBE_HEAVY", "BOTH_BUILD_HEAVY"
CLASSES = (COLD, PROBE_ONLY, BUILD_ONLY, BOTH_PROBE, BOTH_BUILD)


@dataclass(frozen=True)
class HotKey:
    """One skewed value: its class and how often it occurs on either side."""

    key: object
    cls: str
    r: int
    s: int


def classes(r: DataFrame, s: DataFrame, a: str, b: str, rho_r: DataFrame, rho_s: DataFrame, tie: str = "probe") -> DataFrame:
    """(key, cls, r_cnt, s_cnt) of all skewed values; a value's count on its light side is exact, 0 if absent.

    Both inputs are at most 1/p rows, so everything but the two counts is tiny.
    """
    from .stats import recount

    keys = rho_r.select("key").union(rho_s.select("key")).distinct()
    in_r = rho_r.select("key", F.lit(True).alias("in_r"))
    in_s = rho_s.select("key", F.lit(True).alias("in_s"))
    r_cnt = recount(r, a, keys).select("key", F.col("cnt").alias("r_cnt"))
    s_cnt = recount(s, b, keys).select("key", F.col("cnt").alias("s_cnt"))
    out = keys.join(in_r, "key", "left").join(in_s, "key", "left").join(r_cnt, "key", "left").join(s_cnt, "key", "left").fillna(0, ["r_cnt", "s_cnt"])
    probe = (F.col("r_cnt") >= F.col("s_cnt")) if tie == "probe" else (F.col("r_cnt") > F.col("s_cnt"))
    cls = (
        F.when(F.col("in_s").isNull(), PROBE_ONLY).when(F.col("in_r").isNull(), BUILD_ONLY).when(probe, BOTH_PROBE).otherwise(BOTH_BUILD)
    )
    return out.select("key", cls.alias("cls"), "r_cnt", "s_cnt")


def collect(found: DataFrame) -> list[HotKey]:
    """The classes on the driver: at most 2/p rows."""
    return sorted((HotKey(x["key"], x["cls"], x["r_cnt"], x["s_cnt"]) for x in found.collect()), key=lambda h: (-(h.r * h.s), -(h.r + h.s), str(h.key)))


def find(r: DataFrame, s: DataFrame, a: str, b: str, p: float, strict: bool = False, tie: str = "probe", detect=None) -> list[HotKey]:
    """Detect and classify: exact statistics unless another detector (df, key, p) is given."""
    from .stats import exact_skew

    detector = detect or (lambda df, key, p: exact_skew(df, key, p, strict))
    return collect(classes(r, s, a, b, detector(r, a, p), detector(s, b, p), tie))
