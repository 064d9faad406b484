"""Quality rules with adaptive thresholds.

Base measures of every whole text, then per (language, source) a mergeable quantile
sketch of each ratio, then fences from the sketches joined back to filter.

The sketch is a histogram over integer permille bins, single up to EXACT, beyond it a
thousandth of their value wide: two sketches merge by adding counters, its size grows with
the logarithm of the largest value whatever the number of rows, and its rank error is zero
at bin resolution.  Fences hold against the unrounded ratios.  Rows are combined into counters before the shuffle, so a
source with a third of all rows is one small group.

Edge cases: a null or empty text has no words, all measures 0, base_failed, not kept.
Null language or source is a group of its own.  Repeated rows count as often as they
come.  An empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column, map_batches, slices, stage
from .wordhash import Words, buffers, mix64, spans_hash, windows

#: Ratios in permille (word length in tenths), the smallest spread a fence may use, and whether it has a lower side.
RATIOS = {"r_symbols": (20, False), "r_dup_lines": (150, False), "r_repeat": (100, False), "r_word_len": (10, True)}
EXACT = 2048
FENCE = 3
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")

_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[[ord(c) for c in "#*$%&|<>"]] = True
_LEAD = np.ones(256, dtype=bool)
_LEAD[0x80:0xC0] = False
_BLANK = np.zeros(256, dtype=bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True


def _per_text(mask: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    total = np.zeros(len(mask) + 1, dtype=np.int64)
    np.cumsum(mask, out=total[1:])
    return total[offsets[1:]] - total[offsets[:-1]]


def _repeated(key: np.ndarray) -> np.ndarray:
    """Whether each value occurs twice or more."""
    order = np.argsort(key)
    srt = key[order]
    same = np.zeros(len(key), dtype=bool)
    if len(key) > 1:
        eq = srt[1:] == srt[:-1]
        same[1:] |= eq
        same[:-1] |= eq
    out = np.empty(len(key), dtype=bool)
    out[order] = same
    return out


def measure(raw: np.ndarray, offsets: np.ndarray) -> dict[str, np.ndarray]:
    """The base measures of each text of a slice."""
    n = len(offsets) - 1
    words = Words(raw, offsets)
    count = words.counts().astype(np.int64)
    out = {"n_words": count, "word_chars": _per_text(_LEAD[raw] & ~_BLANK[raw], offsets), "n_symbols": _per_text(_SYMBOL[raw], offsets)}
    # lines: spans between line feeds and text bounds
    feed = np.flatnonzero(raw == 10)
    start = np.sort(np.concatenate([offsets[:-1], feed + 1]))
    end = np.sort(np.concatenate([feed, offsets[1:]]))
    text = np.repeat(np.arange(n), 1 + np.searchsorted(feed, offsets[1:]) - np.searchsorted(feed, offsets[:-1]))
    has = np.searchsorted(words.start, start) < np.searchsorted(words.start, end)
    start, end, text = start[has], end[has], text[has]
    line = mix64(spans_hash(raw, start, end) ^ mix64(text.astype(np.uint64), 5), 6)
    order = np.lexsort((line, text))
    later = np.zeros(len(line), dtype=bool)
    if len(line) > 1:
        later[1:] = (line[order][1:] == line[order][:-1]) & (text[order][1:] == text[order][:-1])
    out["n_dup_lines"] = np.bincount(text[order][later], minlength=n).astype(np.int64)
    out["n_lines"] = np.bincount(text, minlength=n).astype(np.int64)
    # words inside five-word windows that the text has twice or more
    owner = words.owner()
    win, inside = windows(words.hashes(), words.first, 5)
    at = np.flatnonzero(inside)
    twice = at[_repeated(mix64(win[at] ^ mix64(owner[at].astype(np.uint64), 7), 8))]
    cover = np.zeros(len(owner) + 6, dtype=np.int64)
    np.add.at(cover, twice, 1)
    np.add.at(cover, twice + 5, -1)
    hit = np.cumsum(cover)[: len(owner)] > 0
    out["n_repeat_words"] = np.bincount(owner[hit], minlength=n).astype(np.int64)
    return out


def base_measures(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, lang, source, measures) of every row; lang or source missing from docs read as null."""
    groups = [F.col(c).cast("string").alias(c) if c in docs.columns else F.lit(None).cast("string").alias(c) for c in ("lang", "source")]
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), *groups, F.col(text_col).cast("string").alias("text"))

    def run(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        parts = [measure(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in slices(offsets)]
        cols = [np.concatenate([p[m] for p in parts]) for m in MEASURES]
        yield pa.RecordBatch.from_arrays(
            [column(batch, c) for c in ("doc_id", "lang", "source")] + [pa.array(c) for c in cols],
            names=["doc_id", "lang", "source", *MEASURES],
        )

    return map_batches(src, run, "doc_id long, lang string, source string, " + ", ".join(f"{m} long" for m in MEASURES))


def with_ratios(base: DataFrame) -> DataFrame:
    # integer division keeps every bin exact
    def whole(top: str, bottom: str, scale: int):
        return F.expr(f"case when {bottom} > 0 then ({scale} * {top}) div {bottom} else 0L end")

    return base.withColumns({
        "r_symbols": whole("n_symbols", "word_chars", 1000),
        "r_dup_lines": whole("n_dup_lines", "n_lines", 1000),
        "r_repeat": whole("n_repeat_words", "n_words", 1000),
        "r_word_len": whole("word_chars", "n_words", 10),
        "base_failed": F.expr("n_words < 10 or 100 * n_repeat_words > 20 * n_words"),
    })


def binned(ratio: str):
    """The lowest value of a ratio's bin: its eleven leading bits."""
    width = F.expr(f"greatest(0, cast(floor(log2(greatest({ratio}, 1L))) as int) - 10)")
    return F.call_function("shiftleft", F.call_function("shiftright", F.col(ratio), width), width)


def sketch(rows: DataFrame) -> DataFrame:
    """Histogram counters (lang, source, measure, bin, n) of the rows that passed the base rules."""
    long = rows.where("not base_failed").select(
        "lang", "source",
        F.explode(F.array(*[F.struct(F.lit(r).alias("measure"), binned(r).alias("bin")) for r in RATIOS])).alias("x"),
    )
    return long.groupBy("lang", "source", F.col("x.measure").alias("measure"), F.col("x.bin").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def merge_sketches(*parts: DataFrame) -> DataFrame:
    """The sketch of the union of the rows of several sketches."""
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("lang", "source", "measure", "bin").agg(F.sum("n").alias("n"))


def fences(counters: DataFrame) -> DataFrame:
    """(lang, source, <ratio>_lo, <ratio>_hi) from the quartiles of each sketch.

    Each sketch has at most EXACT + 1024 * log2(largest / EXACT) counters, so folding its sorted counters is bounded.
    """
    hist = counters.groupBy("lang", "source", "measure").agg(
        F.array_sort(F.collect_list(F.struct("bin", "n"))).alias("h"), F.sum("n").alias("total")
    )

    def quantile(quarters: int):
        return F.aggregate(
            "h", F.struct(F.lit(0).cast("long").alias("c"), F.lit(None).cast("long").alias("q")),
            lambda s, x: F.struct(
                (s["c"] + x["n"]).alias("c"),
                F.when(s["q"].isNotNull(), s["q"]).when((s["c"] + x["n"]) * 4 >= F.col("total") * quarters, x["bin"]).alias("q"),
            ),
            lambda s: s["q"],
        )

    q = hist.select("lang", "source", "measure", quantile(1).alias("q1"), quantile(3).alias("q3"))
    out = []
    for r, (spread, lower) in RATIOS.items():
        width = F.greatest(F.col("q3") - F.col("q1"), F.lit(spread)) * FENCE
        mine = F.col("measure") == r
        out.append(F.max(F.when(mine, F.col("q3") + width)).alias(f"{r}_hi"))
        out.append(F.max(F.when(mine, (F.col("q1") - width) if lower else F.lit(-1))).alias(f"{r}_lo"))
    return q.groupBy("lang", "source").agg(*out)


def apply_rules(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every row with its measures, base_failed and kept."""
    # measured once, read twice: for the sketches and for the filter
    rows = with_ratios(stage(base_measures(docs, id_col, text_col), "measures"))
    limits = fences(sketch(rows)).select(F.col("lang").alias("g_lang"), F.col("source").alias("g_source"), *[f"{r}_{s}" for r in RATIOS for s in ("lo", "hi")])
    joined = rows.join(limits, F.col("lang").eqNullSafe(F.col("g_lang")) & F.col("source").eqNullSafe(F.col("g_source")), "left")
    within = F.lit(True)
    for r in RATIOS:
        within = within & F.coalesce(F.col(r).between(F.col(f"{r}_lo"), F.col(f"{r}_hi")), F.lit(True))
    return joined.withColumn("kept", ~F.col("base_failed") & within).drop("g_lang", "g_source")


def op9(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return apply_rules(docs).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


OP9_SQL = r"""
WITH w AS (
  SELECT doc_id, lang, source, text,
         list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS ls
  FROM documents),
pos AS (SELECT doc_id, unnest(range(1, len(ws) - 3)) AS i, ws FROM w WHERE len(ws) >= 5),
win AS (SELECT doc_id, i, array_to_string(ws[i:i + 4], ' ') AS g FROM pos),
rep AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) t WHERE c > 1),
cov AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM rep, range(0, 5) r(k) GROUP BY doc_id),
m AS (
  SELECT w.doc_id, lang, source, len(ws) AS n_words,
         coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::BIGINT AS word_chars,
         length(regexp_replace(coalesce(text, ''), '[^#*$%&|<>]', '', 'g')) AS n_symbols,
         len(ls) - len(list_distinct(ls)) AS n_dup_lines, len(ls) AS n_lines,
         coalesce(cov.n, 0) AS n_repeat_words
  FROM w LEFT JOIN cov USING (doc_id)),
r AS (
  SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
         CASE WHEN word_chars > 0 THEN (1000 * n_symbols) // word_chars ELSE 0 END AS r1,
         CASE WHEN n_lines > 0 THEN (1000 * n_dup_lines) // n_lines ELSE 0 END AS r2,
         CASE WHEN n_words > 0 THEN (1000 * n_repeat_words) // n_words ELSE 0 END AS r3,
         CASE WHEN n_words > 0 THEN (10 * word_chars) // n_words ELSE 0 END AS r4
  FROM m),
q AS (
  SELECT lang, source,
         quantile_disc((r1 >> greatest(0, floor(log2(greatest(r1, 1)))::INT - 10)) << greatest(0, floor(log2(greatest(r1, 1)))::INT - 10), 0.75) AS a3, quantile_disc((r1 >> greatest(0, floor(log2(greatest(r1, 1)))::INT - 10)) << greatest(0, floor(log2(greatest(r1, 1)))::INT - 10), 0.25) AS a1, quantile_disc((r2 >> greatest(0, floor(log2(greatest(r2, 1)))::INT - 10)) << greatest(0, floor(log2(greatest(r2, 1)))::INT - 10), 0.75) AS b3, quantile_disc((r2 >> greatest(0, floor(log2(greatest(r2, 1)))::INT - 10)) << greatest(0, floor(log2(greatest(r2, 1)))::INT - 10), 0.25) AS b1,
         quantile_disc((r3 >> greatest(0, floor(log2(greatest(r3, 1)))::INT - 10)) << greatest(0, floor(log2(greatest(r3, 1)))::INT - 10), 0.75) AS c3, quantile_disc((r3 >> greatest(0, floor(log2(greatest(r3, 1)))::INT - 10)) << greatest(0, floor(log2(greatest(r3, 1)))::INT - 10), 0.25) AS c1, quantile_disc((r4 >> greatest(0, floor(log2(greatest(r4, 1)))::INT - 10)) << greatest(0, floor(log2(greatest(r4, 1)))::INT - 10), 0.75) AS d3, quantile_disc((r4 >> greatest(0, floor(log2(greatest(r4, 1)))::INT - 10)) << greatest(0, floor(log2(greatest(r4, 1)))::INT - 10), 0.25) AS d1
  FROM r WHERE NOT base_failed GROUP BY lang, source)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines,
       n_repeat_words::BIGINT AS n_repeat_words, base_failed,
       NOT base_failed AND coalesce(r1 <= a3 + 3 * greatest(a3 - a1, 20) AND r2 <= b3 + 3 * greatest(b3 - b1, 150)
         AND r3 <= c3 + 3 * greatest(c3 - c1, 100)
         AND r4 BETWEEN d1 - 3 * greatest(d3 - d1, 10) AND d3 + 3 * greatest(d3 - d1, 10), true) AS kept
FROM r LEFT JOIN q ON r.lang IS NOT DISTINCT FROM q.lang AND r.source IS NOT DISTINCT FROM q.source
"""
