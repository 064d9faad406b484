"""Mixing sources to target weights as a time-varying curriculum, in DataFrame operations only.

Every source has a weight and a schedule: the rate at which it is asked for words at
training time t in [0, 1] is its target times 1 + slope * (2t - 1), whose integral over
[0, 1] is the target.  Its documents, in an order drawn by a keyed hash and repeated in
epochs, fill that demand: the position of a copy is the time at which the source's
cumulative demand reaches the middle of the copy, found by inverting the integral, a
quadratic.  The rows are range-sorted by position.

Targets: the sources share `share` times all words by weight; no target exceeds REPEATS
times its source's words, and what is cut off is shared again by weight among the rest.
A document gets whole repeats; the one at which the target is reached is cut, so each
source gives its target to within rounding.

Running sums are taken in two steps, within (source, slot) and over slots, so that a
source with a third of all rows is dealt over as many tasks as it needs.

Edge cases: null and empty texts have size 0 and take nothing; a null source is a source
of its own, last in order; without words every target is 0.  Repeated rows are separate
documents, ordered by id, then text size.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stage

REPEATS = 3
SLOT_ROWS = 2_500
WEIGHTS = (1, 2, 3)
SLOPES = (0.6, 0.0, -0.6)  # schedules in the order of sources, repeating: rising, flat, falling
_SPACES = "\t\n\u000b\f\r"


def n_words(text: Column) -> Column:
    """Number of maximal runs of other characters than space and the five controls."""
    flat = F.translate(F.coalesce(text, F.lit("")), _SPACES, " " * len(_SPACES))
    return F.size(F.filter(F.split(flat, " "), lambda w: w != "")).cast("long")


def weighted_targets(sizes: DataFrame, share: float = 1.0, repeats: int = REPEATS) -> DataFrame:
    """(source, source_size, weight, slope, target), one row per source.

    The level that fills the caps solves sum(min(level * weight, repeats * size)) = share * total.
    Sorted by size / weight the capped sources are a prefix, so the level follows from
    running sums over the sources: no iteration.
    """
    # ranking the sources needs them in one order: a task holds one row of six numbers per source, so
    # that ten million of them still fit; their documents aren't touched
    order = Window.orderBy(F.col("source").isNull(), "source")
    ranked = sizes.withColumn("place", F.row_number().over(order) - 1)
    weight = F.element_at(F.array(*[F.lit(w) for w in WEIGHTS]), F.pmod("place", F.lit(len(WEIGHTS))).cast("int") + 1)
    slope = F.element_at(F.array(*[F.lit(s) for s in SLOPES]), F.pmod("place", F.lit(len(SLOPES))).cast("int") + 1)
    ranked = ranked.withColumns({"weight": weight.cast("double"), "slope": slope, "cap": (F.col("source_size") * repeats).cast("double")})
    by_level = Window.orderBy(F.col("cap") / F.col("weight"), "place")
    before = by_level.rowsBetween(Window.unboundedPreceding, -1)
    rest = by_level.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everything = by_level.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    filled = ranked.withColumns({
        "goal": F.sum("source_size").over(everything) * F.lit(float(share)),
        "capped": F.coalesce(F.sum("cap").over(before), F.lit(0.0)),
        "open": F.sum("weight").over(rest),
    })
    # the level if this source is the first that isn't capped; it is so if the level is below its own cap
    filled = filled.withColumn("level", (F.col("goal") - F.col("capped")) / F.col("open"))
    filled = filled.withColumn("fits", F.col("level") <= F.col("cap") / F.col("weight"))
    level = F.min(F.when(F.col("fits"), F.struct(F.col("cap") / F.col("weight"), "place", "level"))).over(everything)["level"]
    target = F.least("cap", F.coalesce(level * F.col("weight"), F.col("cap")))
    return filled.withColumn("target", target).select("source", "source_size", "weight", "slope", "target")


def curriculum(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", share: float = 1.0, repeats: int = REPEATS, seed: int = 17) -> DataFrame:
    """(doc_id, source, size, source_size, target, taken, position) of every row of docs.

    `position` is the training time of the first copy, null for rows that the mix doesn't take.
    """
    # the texts are read once; what follows works on sizes
    rows = stage(docs.select(
        F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), n_words(F.col(text_col).cast("string")).alias("size")
    ), "sizes")
    # slots: enough that each holds about SLOT_ROWS rows; computed from counts of each source
    slot_count = rows.groupBy("source").agg(F.ceil(F.count(F.lit(1)) / SLOT_ROWS).cast("int").alias("slots"), F.sum("size").alias("source_size"))
    targets = weighted_targets(slot_count.select("source", "source_size"), share, repeats)
    plan = slot_count.select(F.col("source").alias("s"), "slots").join(targets, F.col("s").eqNullSafe(F.col("source"))).select("s", "slots", "source_size", "slope", "target")
    draw = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary")), 1, 15), 16, 10).cast("long")
    rows = rows.withColumn("draw", draw).join(plan, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    # equal slices of the hash range, so that slots follow each other in the drawn order
    unit = F.col("draw").cast("double") / F.lit(float(2**60))
    rows = rows.withColumn("slot", F.least(F.floor(unit * F.col("slots")).cast("int"), F.col("slots") - 1))
    slots = rows.groupBy("source", "slot").agg(F.sum("size").alias("slot_size"))
    over = Window.partitionBy("source").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    slots = slots.select(F.col("source").alias("s"), F.col("slot").alias("k"), F.coalesce(F.sum("slot_size").over(over), F.lit(0)).alias("base"))
    rows = rows.join(slots, F.col("source").eqNullSafe(F.col("s")) & (F.col("slot") == F.col("k"))).drop("s", "k")
    within = Window.partitionBy("source", "slot").orderBy("draw", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("start", F.col("base") + F.coalesce(F.sum("size").over(within), F.lit(0)))
    # whole epochs for everyone, then the documents that the rest of the target reaches
    goal = F.round("target").cast("long")
    epochs = F.when(F.col("source_size") > 0, F.floor(goal / F.col("source_size"))).otherwise(0).cast("long")
    rest = goal - epochs * F.col("source_size")
    taken = epochs * F.col("size") + F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), rest - F.col("start")))
    rows = rows.withColumn("taken", taken.cast("long"))
    rows = rows.withColumn("position", F.when(F.col("taken") > 0, position_of(F.lit(0))))
    return rows.select("doc_id", "source", "size", "source_size", "target", "taken", "position", "start", "slope")


def position_of(copy: Column) -> Column:
    """The training time of a copy: when the source's demand so far meets the middle of its words.

    Demand so far at time t is target * ((1 - slope) t + slope t^2); copy c of a document starts
    c times the source's size after its first, and the last copy may be cut.
    """
    words = F.least("size", F.col("taken") - copy * F.col("size"))
    share_at = F.least(F.lit(1.0), (F.col("start") + copy * F.col("source_size") + words / 2) / F.when(F.col("target") > 0, F.col("target")))
    a, b = F.col("slope"), 1 - F.col("slope")
    t = F.when(F.abs(a) < 1e-9, share_at).otherwise((-b + F.sqrt(F.greatest(F.lit(0.0), b * b + 4 * a * share_at))) / (2 * F.when(F.abs(a) >= 1e-9, a)))
    return F.least(F.lit(1.0), t)


def copies(mixed: DataFrame) -> DataFrame:
    """One row per copy of each taken document, (doc_id, copy, position), range-sorted by training position."""
    rows = mixed.where("taken > 0").withColumn("copy", F.explode(F.sequence(F.lit(0), _n_copies() - 1)))
    return rows.withColumn("position", position_of(F.col("copy"))).select("doc_id", "copy", "position").orderBy("position", "doc_id", "copy")


def _n_copies() -> Column:
    return F.ceil(F.col("taken") / F.when(F.col("size") > 0, F.col("size"))).cast("int")


def mixture(docs: DataFrame, **options) -> DataFrame:
    """docs, with all their columns, as the mix takes them: a row per copy, range-sorted by training position.

    Rows that share an id are drawn together, and so are those without one: each comes as often,
    and at the same times, as the one of them that the mix takes most of.
    """
    drawn = curriculum(docs, **options)
    once = drawn.groupBy("doc_id").agg(F.max(F.struct("taken", "size", "source_size", "target", "start", "slope")).alias("m")).select("doc_id", "m.*")
    times = F.transform(F.sequence(F.lit(0), _n_copies() - 1), lambda c: position_of(c))
    plan = once.where("taken > 0").select(F.col("doc_id").alias("__mix_id"), times.alias("__mix_times"))
    rows = docs.join(plan, F.col("doc_id").eqNullSafe(F.col("__mix_id")))
    rows = rows.select(*[F.col(c) for c in docs.columns], F.posexplode("__mix_times").alias("__mix_copy", "__mix_at"))
    return rows.orderBy("__mix_at", "doc_id", "__mix_copy").select(docs.columns)


def op6(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    mixed = curriculum(docs).select(
        "doc_id", "size", "source_size", F.round("target", 4).alias("target"), "taken", F.round("position", 7).alias("position")
    )
    return mixed.orderBy("position", "doc_id")


OP6_SQL = r"""
WITH w AS (
  SELECT doc_id, source, len(list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> ''))::BIGINT AS size,
         ('0x' || substr(md5('17:' || doc_id), 1, 15))::BIGINT AS draw
  FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source IS NULL, source) - 1 AS place FROM w GROUP BY source),
r AS (SELECT *, (place % 3 + 1)::DOUBLE AS weight, [0.6, 0.0, -0.6][place % 3 + 1]::DOUBLE AS slope, 3.0::DOUBLE * source_size AS cap FROM s),
f AS (
  SELECT *, sum(source_size) OVER () AS goal,
         coalesce(sum(cap) OVER (ORDER BY cap / weight, place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS capped,
         sum(weight) OVER (ORDER BY cap / weight, place ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS open_w
  FROM r),
l AS (SELECT arg_min((goal - capped) / open_w, place + 1e9 * (cap / weight)) AS level FROM f WHERE (goal - capped) / open_w <= cap / weight),
t AS (SELECT f.*, least(cap, coalesce(level * weight, cap)) AS target FROM f, l),
c AS (
  SELECT w.doc_id, size, t.source_size, target, slope,
         coalesce(sum(size) OVER (PARTITION BY w.source ORDER BY draw, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start,
         round(target)::BIGINT AS goal_n
  FROM w JOIN t ON w.source IS NOT DISTINCT FROM t.source),
k AS (
  SELECT *, CASE WHEN source_size > 0 THEN goal_n // source_size ELSE 0 END AS epochs FROM c),
m AS (
  SELECT *, (epochs * size + greatest(0, least(size, goal_n - epochs * source_size - start)))::BIGINT AS taken FROM k),
p AS (SELECT *, CASE WHEN target > 0 THEN least(1.0, (start + least(size, taken) / 2) / target) END AS x FROM m)
SELECT doc_id, size, source_size, round(target, 4) AS target, taken,
       round(CASE WHEN taken > 0 THEN least(1.0, CASE WHEN abs(slope) < 1e-9 THEN x
         ELSE (slope - 1 + sqrt(greatest(0.0, (1 - slope) * (1 - slope) + 4 * slope * x))) / (2 * slope) END) END, 7) AS position
FROM p
"""
