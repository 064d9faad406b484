"""Substring deduplication: words covered by a fixed-length window that an earlier document also has.

Every window of WINDOW words gets a Rabin-Karp hash.  Windows are dealt to buckets by
their minimizer (the smallest hash of the GRAM-word runs inside), so neighbouring windows
travel together and equal windows always meet.  A map task packs the windows of a slice
of documents per bucket, hashes sorted by bucket, after combining equal windows of the
slice: of those only the ones of the smallest doc_id go on, the others are decided there.
Each bucket finds the smallest doc_id of every hash; windows of larger doc_ids are flagged,
and flagged windows come back as runs, merged per document into maximal removal intervals.

A minimizer that a bounded sample shows to be very common is dealt by window hash instead
(this changes the placement only, not the result).

The hash has 64 bits, and only windows of one bucket are compared: a bucket holds the windows of
BUCKET_BYTES of text, some 10**6, whatever the size of the corpus, so the false flags expected
are below 10**12 / 2**65 a bucket: under one in 100 TB of text, whose buckets are 2 * 10**7.
Windows of very common minimizers, dealt by their own hash, lack that; they add n**2 / 2**65 for
n of them.

Edge cases: a null or empty text has no words; texts under WINDOW words lose nothing; a
null doc_id takes no part and its text is kept; rows that share a doc_id are one document
and are expected to hold the same text.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import column, map_batches, slices
from .wordhash import Words, buffers, mix64, windows

WINDOW = 13
GRAM = 4
BUCKET_BYTES = 5_000_000  # text bytes whose windows make one bucket
SAMPLE_ROWS = 2000  # rows in which common minimizers are looked for
PACKED = "bucket int, ids binary, runs binary, hashes binary"


def sliding_min(a: np.ndarray, width: int) -> np.ndarray:
    """Minimum of a[i : i + width] for each i, by doubling; the tail repeats what is left."""
    out, have = a.copy(), 1
    while have < width:
        step = min(have, width - have)
        out[: len(out) - step] = np.minimum(out[: len(out) - step], out[step:])
        have += step
    return out


class Slice:
    """Hashes of the windows of a slice of texts, and the bucket of each."""

    def __init__(self, raw, offsets, window: int, buckets: int, hot: np.ndarray):
        self.words = Words(raw, offsets)
        h = self.words.hashes()
        self.first = self.words.first
        self.hash, self.inside = windows(h, self.first, window)
        gram = min(GRAM, window)
        if len(h):
            self.mini = sliding_min(windows(h, self.first, gram, 1)[0], window - gram + 1)
        else:
            self.mini = h
        key = mix64(self.mini, 21)
        if len(hot) and len(key):
            at = np.minimum(np.searchsorted(hot, key), len(hot) - 1)
            key = np.where(hot[at] == key, mix64(self.hash, 22), key)
        self.bucket = (key % np.uint64(buckets)).astype(np.int32)


def runs_of(at: np.ndarray, *same: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first, length) of the maximal runs of consecutive values of `at` along which `same` don't change."""
    if not len(at):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    new = np.ones(len(at), dtype=bool)
    new[1:] = at[1:] != at[:-1] + 1
    for s in same:
        new[1:] |= s[1:] != s[:-1]
    first = np.flatnonzero(new)
    return first, np.diff(np.append(first, len(at)))


def _pack(ids: np.ndarray, doc: np.ndarray, start: np.ndarray, length: np.ndarray, z) -> tuple[bytes, bytes]:
    used, index = np.unique(doc, return_inverse=True)
    table = np.concatenate([index.astype(np.uint32), start.astype(np.uint32), length.astype(np.uint32)])
    return z.compress(ids[used].astype(np.int64).tobytes()), z.compress(table.tobytes())


def _unpack(ids: bytes, runs: bytes, z) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    table = np.frombuffer(z.decompress(runs), dtype=np.uint32).reshape(3, -1).astype(np.int64)
    return np.frombuffer(z.decompress(ids), dtype=np.int64)[table[0]], table[1], table[2]


def pack_slice(ids: np.ndarray, raw: np.ndarray, offsets: np.ndarray, window: int, buckets: int, hot: np.ndarray) -> Iterator[tuple]:
    """Rows of PACKED for a slice; a row without hashes holds runs that are already decided."""
    s = Slice(raw, offsets, window, buckets, hot)
    k = np.flatnonzero(s.inside)
    if not len(k):
        return
    z = zstandard.ZstdCompressor(level=1)
    doc = s.words.owner()[k]
    pos = k - s.first[doc]
    h = s.hash[k]
    order = np.argsort(h)
    edge = np.flatnonzero(np.concatenate([[True], h[order][1:] != h[order][:-1]]))
    least = np.minimum.reduceat(ids[doc][order], edge)
    later = np.empty(len(k), dtype=bool)
    later[order] = ids[doc][order] > np.repeat(least, np.diff(np.append(edge, len(k))))
    if later.any():
        d, p = doc[later], pos[later]
        at, length = runs_of(p, d)
        yield (int(abs(int(ids[d[0]])) % buckets), *_pack(ids, d[at], p[at], length, z), b"")
    keep = np.flatnonzero(~later)
    b, d, p, h = s.bucket[k[keep]], doc[keep], pos[keep], h[keep]
    at, length = runs_of(p, d, b)
    by = np.argsort(b[at], kind="stable")
    at, length = at[by], length[by]
    run_bucket = b[at]
    cut = np.concatenate([[0], np.flatnonzero(run_bucket[1:] != run_bucket[:-1]) + 1, [len(at)]]) if len(at) else np.zeros(1, int)
    ends = np.concatenate([[0], np.cumsum(length)])
    gathered = h[np.repeat(at - ends[:-1], length) + np.arange(ends[-1])]
    for lo, hi in zip(cut[:-1], cut[1:]):
        part = slice(lo, hi)
        yield (
            int(run_bucket[lo]), *_pack(ids, d[at[part]], p[at[part]], length[part], z), gathered[ends[lo] : ends[hi]].tobytes()
        )


def judge(rows: list[tuple[bytes, bytes, bytes]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(doc_id, start, length) of the flagged runs of one bucket."""
    z = zstandard.ZstdDecompressor()
    done, doc, start, size, hashes = [], [], [], [], []
    for ids, runs, h in rows:
        d, s, n = _unpack(ids, runs, z)
        if h:
            doc.append(d), start.append(s), size.append(n), hashes.append(np.frombuffer(h, dtype=np.uint64))
        else:
            done.append((d, s, n))
    if hashes:
        doc, start, size, h = np.concatenate(doc), np.concatenate(start), np.concatenate(size), np.concatenate(hashes)
        run = np.repeat(np.arange(len(doc)), size)
        own = doc[run]
        order = np.argsort(h)
        srt = h[order]
        edge = np.flatnonzero(np.concatenate([[True], srt[1:] != srt[:-1]]))
        by = own[order]
        least = np.minimum.reduceat(by, edge)
        flag = np.empty(len(h), dtype=bool)
        flag[order] = by > np.repeat(least, np.diff(np.append(edge, len(h))))
        at = np.flatnonzero(flag)
        if len(at):
            begin = np.cumsum(size) - size
            pos = start[run[at]] + at - begin[run[at]]
            first, length = runs_of(pos, run[at])
            done.append((own[at[first]], pos[first], length))
    if not done:
        return (np.zeros(0, np.int64),) * 3
    return tuple(np.concatenate(x) for x in zip(*done))


def hot_minimizers(docs: DataFrame, window: int, buckets: int, n_rows: int) -> np.ndarray:
    """Minimizers that make up over half a bucket's fair share of a bounded sample; at most 2 x buckets of them."""
    if buckets < 2 or not n_rows:
        return np.zeros(0, np.uint64)
    slots = 1 << 20
    bound = min(slots, int(slots * SAMPLE_ROWS / n_rows) + 1)
    sample = docs.where(F.pmod(F.xxhash64(F.lit("minimizers"), "doc_id"), F.lit(slots)) < bound)

    def run(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        for a, b in slices(offsets):
            s = Slice(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], window, buckets, np.zeros(0, np.uint64))
            key, n = np.unique(mix64(s.mini[s.inside], 21), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(n.astype(np.int64))], names=["k", "n"])

    counts = map_batches(sample, run, "k long, n long").groupBy("k").agg(F.sum("n").alias("n"))
    total = counts.agg(F.sum("n")).first()[0] or 0
    # a minimizer seen in a few documents of the sample alone isn't common
    rows = counts.where(F.col("n") > max(total / (2 * buckets), 60)).orderBy(F.desc("n"), "k").limit(2 * buckets).collect()
    return np.sort(np.array([r["k"] for r in rows], dtype=np.int64).view(np.uint64))


def flagged_runs(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """(doc_id, runs: array<struct<start, len>>) of documents with a flagged window; docs: (doc_id, text)."""
    spark = docs.sparkSession
    docs = docs.where("doc_id is not null")
    size = docs.agg(F.sum(F.octet_length("text")).alias("b"), F.count(F.lit(1)).alias("n")).first()
    at_least = min(64, int(spark.conf.get("spark.sql.shuffle.partitions")))
    buckets = max(at_least, -(-int(size["b"] or 0) // BUCKET_BYTES))
    hot = hot_minimizers(docs, window, buckets, size["n"])

    def pack(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        ids = column(batch, "doc_id").to_numpy()
        for a, b in slices(offsets):
            rows = list(pack_slice(ids[a:b], raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], window, buckets, hot))
            if rows:
                kinds = (pa.int32(), pa.binary(), pa.binary(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=["bucket", "ids", "runs", "hashes"])

    def reduce(table: pa.Table) -> pa.Table:
        rows = zip(*(table.column(c).to_pylist() for c in ("ids", "runs", "hashes")))
        doc, start, length = judge(list(rows))
        return pa.table({"doc_id": doc, "start": start.astype(np.int32), "len": length.astype(np.int32)})

    packed = map_batches(docs.select("doc_id", "text"), pack, PACKED)
    runs = packed.groupBy("bucket").applyInArrow(reduce, "doc_id long, start int, len int")
    return runs.groupBy("doc_id").agg(F.collect_list(F.struct("start", "len")).alias("runs"))


def covered(n_words: int, runs: list[dict], window: int) -> np.ndarray:
    """Which words lie in a flagged window, from runs of flagged window starts."""
    mark = np.zeros(n_words + 1, dtype=np.int64)
    for r in runs:
        mark[r["start"]] += 1
        mark[min(r["start"] + r["len"] - 1 + window, n_words)] -= 1
    return np.cumsum(mark)[:n_words] > 0


_Z, _RUNS, _KEY = "__removal_text", "__removal_runs", "__removal_key"


def _joined(docs: DataFrame, window: int) -> DataFrame:
    """Every row with its text, compressed for the shuffle, and its runs; other columns as they are."""
    rest = [f for f in docs.schema.fields if f.name != "text"]

    def shrink(batch: pa.RecordBatch):
        z = zstandard.ZstdCompressor(level=1)
        blob = [None if not t.is_valid else z.compress(t.as_buffer()) for t in column(batch, "text")]
        yield pa.RecordBatch.from_arrays([column(batch, f.name) for f in rest] + [pa.array(blob, pa.binary())], names=[f.name for f in rest] + [_Z])

    small = map_batches(docs, shrink, T.StructType([*rest, T.StructField(_Z, T.BinaryType())]))
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    runs = flagged_runs(keyed, window).select(F.col("doc_id").alias(_KEY), F.col("runs").alias(_RUNS))
    return small.join(runs.hint("shuffle_hash"), F.col("doc_id") == F.col(_KEY), "left").drop(_KEY)


def removal_digest(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256) of every row."""

    def finish(batch: pa.RecordBatch):
        z = zstandard.ZstdDecompressor()
        n_words, n_removed, sha = [], [], []
        for blob, runs in zip(column(batch, _Z).to_pylist(), column(batch, _RUNS).to_pylist()):
            words = z.decompress(blob).split() if blob else []
            n_words.append(len(words))
            if runs:
                gone = covered(len(words), runs, window)
                words = [words[i] for i in np.flatnonzero(~gone)]
            n_removed.append(n_words[-1] - len(words))
            sha.append(hashlib.sha256(b" ".join(words)).hexdigest())
        yield pa.RecordBatch.from_arrays(
            [column(batch, "doc_id"), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(sha)],
            names=["doc_id", "n_words", "n_removed", "kept_sha256"],
        )

    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_batches(_joined(slim, window), finish, "doc_id long, n_words long, n_removed long, kept_sha256 string")


def cut_text(text: bytes, runs: list[dict], window: int) -> bytes:
    """The text without its removal intervals; each goes from its first word to the start of the next kept word."""
    raw = np.frombuffer(text, dtype=np.uint8)
    words = Words(raw, np.array([0, len(raw)]))
    gone = covered(len(words.start), runs, window)
    at, length = runs_of(np.flatnonzero(gone))
    first = np.flatnonzero(gone)[at]
    out, done = [], 0
    for f, n in zip(first, length):
        out.append(text[done : words.start[f]])
        done = int(words.start[f + n]) if f + n < len(words.start) else len(text)
    out.append(text[done:])
    return b"".join(out)


def remove_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """docs, with all their columns, and each text without its removal intervals; a null text stays null."""
    names = docs.columns

    def finish(batch: pa.RecordBatch):
        z = zstandard.ZstdDecompressor()
        text = []
        for blob, runs in zip(column(batch, _Z).to_pylist(), column(batch, _RUNS).to_pylist()):
            t = None if blob is None else z.decompress(blob)
            text.append(None if t is None else (cut_text(t, runs, window) if t and runs else t).decode())
        new = pa.array(text, pa.string())
        yield pa.RecordBatch.from_arrays([new if c == "text" else column(batch, c) for c in names], names=names)

    return map_batches(_joined(docs, window), finish, docs.schema)


def op10(spark, sf_dir: str) -> DataFrame:
    return removal_digest(spark.read.parquet(f"{sf_dir}/documents.parquet"))


OP10_SQL = r"""
WITH w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
win AS (
  SELECT doc_id, i, array_to_string(ws[i:i + 12], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 11)) AS i FROM w WHERE len(ws) >= 13) t),
hit AS (SELECT doc_id, i FROM (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY g) AS least FROM win) t WHERE least < doc_id),
gone AS (SELECT doc_id, list(DISTINCT i + k) AS ps FROM hit, range(0, 13) r(k) GROUP BY doc_id)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(len(ps), 0)::BIGINT AS n_removed,
       sha256(array_to_string(CASE WHEN ps IS NULL THEN ws ELSE list_transform(list_filter(range(1, len(ws) + 1), lambda j: NOT list_contains(ps, j)), lambda j: ws[j]) END, ' ')) AS kept_sha256
FROM w LEFT JOIN gone USING (doc_id)
"""
