"""Bounded training samples: the only rows that a model is fitted on."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def bounded_sample(rows: DataFrame, id_col: str, most: int) -> list:
    """At most `most` rows, chosen by a hash of the id: the same rows for the same table.

    A hash threshold keeps about 1.25 x `most` rows in the scan's tasks, so that what is
    sorted does not grow with the table.
    """
    total = rows.count()
    if not total:
        return []
    buckets = 1 << 20
    bound = min(buckets, int(buckets * (1.25 * most + 50) / total) + 1)
    key = F.xxhash64(F.lit("sample"), F.col(id_col))
    kept = rows.where(F.pmod(key, F.lit(buckets)) < bound)
    return kept.orderBy(key, id_col).limit(most).collect()


def crc_mod(id_col: str, m: int) -> Column:
    """crc32 of the id as text, modulo m."""
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(m))
