"""b-bit MinHash near-duplicates: links confirmed on whole shingle sets, one component id per document.

1. One pass over the texts makes, per document, the size and digest of its shingle set,
   PERMUTATIONS minima, of which BITS low bits are kept and packed, the keys of the bands,
   and the text compressed; the result is staged.
2. Documents with equal sets are one class, represented by its smallest id.
3. Band keys shared by several classes make groups.  Inside a group, or a block of a large
   one, the packed signatures are compared by counting equal bit fields, corrected for
   chance agreement, and a spanning forest of the pairs above a generous cutoff goes on:
   fewer edges than members, never all pairs.
4. The likely pairs are confirmed on the whole sets, and confirmed links make components.
5. The proposed pairs, confirmed or not, make clusters.  In clusters with several components
   the members' whole sets are compared as bit rows, block by block and across components,
   so no link inside a cluster that could join two components is left out and no pairs are
   emitted for it.  A link is lost only if its estimate is MARGIN too low (under 1 in 10,000).

Edge cases: a null or empty text, or one without words, has an empty set and no links;
with fewer words than a shingle the whole sequence is the one shingle.  A null id is
passed through with a null component and kept.  Repeated rows are one class.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import column, components, map_batches, release, slices, stage
from .grouping import block_rows, join_components, open_blocks, open_clusters, propose
from .wordhash import Words, buffers, mix64, windows

PERMUTATIONS = 128
BITS = 4
BANDS, ROWS = 24, 5
MARGIN = 0.16  # five standard errors of the estimate: below, a pair isn't looked at
LIKELY = 0.02  # within this of the threshold and above, a pair is confirmed at once
CLUSTER_BLOCK = 512
_RNG = np.random.default_rng(20240607)
_A = (_RNG.integers(0, 1 << 32, PERMUTATIONS, dtype=np.uint64) | np.uint64(1)).astype(np.uint32)
_B = _RNG.integers(0, 1 << 32, PERMUTATIONS, dtype=np.uint64).astype(np.uint32)
_FIELD = np.uint64(0x1111111111111111)
_STEP = 1 << 15


def shingles(words: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash, text index) of every shingle, in text order; texts of fewer than k words have one."""
    h, count = words.hashes(), words.counts()
    win, inside = windows(h, words.first, k)
    for c in range(1, k):
        short = words.first[:-1][count == c]
        if len(short):
            win[short] = windows(h, words.first, c, c)[0][short]
            inside[short] = True
    at = np.flatnonzero(inside)
    return win[at], words.owner()[at]


def distinct(sh: np.ndarray, own: np.ndarray) -> np.ndarray:
    """Indices of the first of each (text, shingle)."""
    _, at = np.unique(mix64(sh ^ mix64(own.astype(np.uint64), 31), 32), return_index=True)
    return np.sort(at)


def minima(sh: np.ndarray, own: np.ndarray, texts: np.ndarray) -> np.ndarray:
    """PERMUTATIONS minima of the shingles of each of `texts`, which all have one."""
    x = (sh >> np.uint64(32)).astype(np.uint32)
    first = np.searchsorted(own, texts)
    out = np.empty((len(texts), PERMUTATIONS), dtype=np.uint32)
    at = 0
    while at < len(texts):  # blocks that fit the cache
        upto = max(at + 1, int(np.searchsorted(first, first[at] + _STEP)))
        lo, hi = first[at], first[upto] if upto < len(texts) else len(x)
        part, starts = x[lo:hi], first[at:upto] - lo
        for k in range(PERMUTATIONS):
            out[at:upto, k] = np.minimum.reduceat(part * _A[k] + _B[k], starts)
        at = upto
    return out


def packed(m: np.ndarray) -> np.ndarray:
    """BITS low bits of each minimum, 64 / BITS to a word."""
    per = 64 // BITS
    low = (m & np.uint32((1 << BITS) - 1)).astype(np.uint64).reshape(len(m), PERMUTATIONS // per, per)
    return np.bitwise_or.reduce(low << (np.arange(per, dtype=np.uint64) * np.uint64(BITS)), axis=2)


def band_keys(m: np.ndarray) -> np.ndarray:
    out = np.empty((len(m), BANDS), dtype=np.uint64)
    for b in range(BANDS):
        key = np.full(len(m), b, dtype=np.uint64)
        for r in range(ROWS):
            key = mix64(key ^ m[:, b * ROWS + r].astype(np.uint64), 41 + r)
        out[:, b] = key
    return out


def similarity(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Estimated Jaccard similarity of packed signatures, corrected for chance agreement of BITS bits."""
    x = a ^ b
    x |= x >> np.uint64(1)
    x |= x >> np.uint64(2)
    differ = np.bitwise_count(x & _FIELD).sum(axis=-1, dtype=np.int64)
    chance = 1 / (1 << BITS)
    return ((1 - differ / PERMUTATIONS) - chance) / (1 - chance)


def features(docs: DataFrame, k: int) -> DataFrame:
    """(doc_id, n, d1, d2, sig, bands, z) of every row with an id."""

    def run(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        ids = column(batch, "doc_id")
        z = zstandard.ZstdCompressor(level=1)
        for a, b in slices(offsets):
            part, off = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
            words = Words(part, off, lower=True)
            sh, own = shingles(words, k)
            at = distinct(sh, own)
            m = b - a
            n = np.bincount(own[at], minlength=m).astype(np.int64)
            digest = []
            for seed in (33, 34):
                v = mix64(sh[at], seed)
                total = np.zeros(m, dtype=np.uint64)
                np.add.at(total, own[at], v)
                digest.append(total.view(np.int64))
            texts = np.flatnonzero(n > 0)
            low = minima(sh, own, texts)
            sig: list = [None] * m
            bands: list = [None] * m
            for i, s, key in zip(texts, packed(low), band_keys(low).view(np.int64)):
                sig[i], bands[i] = s.tobytes(), key
            blob = [z.compress(part[off[i] : off[i + 1]].tobytes()) for i in range(m)]
            yield pa.RecordBatch.from_arrays(
                [ids.slice(a, m), pa.array(n), pa.array(digest[0]), pa.array(digest[1]), pa.array(sig, pa.binary()),
                 pa.array(bands, pa.list_(pa.int64())), pa.array(blob, pa.binary())],
                names=["doc_id", "n", "d1", "d2", "sig", "bands", "z"],
            )

    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("doc_id is not null")
    return map_batches(src, run, "doc_id long, n long, d1 long, d2 long, sig binary, bands array<long>, z binary")


def confirm(pairs: DataFrame, feats: DataFrame, k: int, percent: int) -> DataFrame:
    """The pairs (a, b) with 100 * intersection >= percent * union of their whole sets."""
    z = feats.select(F.col("doc_id"), "z")
    joined = (
        pairs.join(z.select(F.col("doc_id").alias("a"), F.col("z").alias("za")), "a")
        .join(z.select(F.col("doc_id").alias("b"), F.col("z").alias("zb")), "b")
    )

    def run(batch: pa.RecordBatch):
        za, zb = column(batch, "za"), column(batch, "zb")
        step = 250
        for lo in range(0, batch.num_rows, step):
            m = min(step, batch.num_rows - lo)
            d = zstandard.ZstdDecompressor()
            sets = []
            for side in (za, zb):
                texts = [d.decompress(t) for t in side.slice(lo, m).to_pylist()]
                off = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
                sh, own = shingles(Words(np.frombuffer(b"".join(texts), dtype=np.uint8), off, lower=True), k)
                at = distinct(sh, own)
                sets.append((mix64(sh[at] ^ mix64(own[at].astype(np.uint64), 31), 32), own[at]))
            (ka, oa), (kb, ob) = sets
            _, ia, _ = np.intersect1d(ka, kb, assume_unique=True, return_indices=True)
            both = np.bincount(oa[ia], minlength=m)
            union = np.bincount(oa, minlength=m) + np.bincount(ob, minlength=m) - both
            ok = np.flatnonzero(100 * both >= percent * union)
            if len(ok):
                yield pa.RecordBatch.from_arrays([column(batch, c).slice(lo, m).take(pa.array(ok)) for c in ("a", "b")], names=["a", "b"])

    return map_batches(joined.select("a", "b", "za", "zb"), run, "a long, b long")


def exact(k: int, percent: int):
    """Functions for join_components: sets of whole texts as bit rows over shared shingles, and the exact test."""

    def load(blobs: list[bytes]):
        d = zstandard.ZstdDecompressor()
        texts = [d.decompress(t) for t in blobs]
        off = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
        sh, own = shingles(Words(np.frombuffer(b"".join(texts), dtype=np.uint8), off, lower=True), k)
        at = distinct(sh, own)
        sh, own = sh[at], own[at]
        size = np.bincount(own, minlength=len(texts))
        _, index, count = np.unique(sh, return_inverse=True, return_counts=True)
        shared = count[index] > 1  # a shingle of one member alone can't be in an intersection
        place = np.cumsum(count > 1) - 1
        bits = np.zeros((len(texts), (int((count > 1).sum()) + 63) // 64), dtype=np.uint64)
        col = place[index[shared]]
        np.bitwise_or.at(bits, (own[shared], col // 64), np.uint64(1) << (col % 64).astype(np.uint64))
        return bits, size

    def linked(data, i: int, rest: np.ndarray) -> np.ndarray:
        bits, size = data
        both = np.bitwise_count(bits[i] & bits[rest]).sum(axis=1, dtype=np.int64)
        return 100 * both >= percent * (size[i] + size[rest] - both)

    return load, linked


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of every row of docs (doc_id, text)."""
    feats = stage(features(docs, k), "minhash")
    classes = feats.where("n > 0").groupBy("n", "d1", "d2").agg(F.min("doc_id").alias("class_id"))
    # staged, so that the join deals both sides itself and may split a large group of copies
    classes = stage(classes, "classes")
    member = feats.select("doc_id", "n", "d1", "d2").join(classes, ["n", "d1", "d2"], "left").select("doc_id", "n", "class_id")
    member = stage(member, "classes")
    reps = member.where("doc_id = class_id").select("doc_id").distinct()
    keyed = feats.select("doc_id", "bands").join(reps, "doc_id", "left_semi").select(F.explode("bands").alias("key"), F.col("doc_id").alias("id"))
    keyed = keyed.groupBy("key", "id").agg(F.lit(1).alias("one")).drop("one")
    shared = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("c"), F.min("id").alias("lead")).where("c > 1")
    groups = stage(keyed.join(shared, "key"), "groups")
    sigs = feats.select(F.col("doc_id").alias("id"), "sig").join(groups.select("id").distinct(), "id", "left_semi")
    sigs = stage(sigs.dropDuplicates(["id"]), "signatures")
    cutoff, least = percent / 100 - MARGIN, percent / 100

    def confirmed(pairs: DataFrame) -> DataFrame:
        return stage(confirm(pairs.where(F.col("s") >= least - LIKELY).select("a", "b"), feats, k, percent), "links")

    pairs = stage(propose(block_rows(groups, sigs), similarity, cutoff, least), "pairs")
    links = confirmed(pairs)
    comp = components(links)
    crossing = open_blocks(groups, sigs, comp)
    if crossing is not None:
        more = stage(propose(crossing, similarity, cutoff, least), "pairs")
        links = stage(links.union(confirmed(more)), "links")
        pairs, comp = pairs.union(more), components(links)
    clusters = components(pairs)
    texts = feats.select(F.col("doc_id").alias("id"), F.col("z").alias("payload")).dropDuplicates(["id"])
    more = stage(join_components(open_clusters(clusters, comp, texts, CLUSTER_BLOCK), *exact(k, percent)), "links")
    if more.limit(1).count():
        comp = components(links.union(more))
    release(feats, classes, groups, sigs, pairs, links, clusters, more)
    out = member.join(comp.withColumnRenamed("node", "class_id"), "class_id", "left").select(
        "doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "class_id", "doc_id").alias("component_id")
    ).withColumn("kept", F.col("doc_id") == F.col("component_id"))
    lost = docs.where("doc_id is null").select(
        F.lit(None).cast("long").alias("doc_id"), F.lit(0).cast("long").alias("n_shingles"), F.lit(None).cast("long").alias("component_id"), F.lit(True).alias("kept")
    )
    return out.union(lost)


def drop_near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """docs, with all their columns, and of each component the document with the smallest id, once.

    Rows without an id stay.
    """
    kept = near_duplicates(docs, k, percent).where("kept and doc_id is not null").select("doc_id").distinct()
    rows = docs.where("doc_id is not null").join(kept, "doc_id", "left_semi")
    once = F.row_number().over(Window.partitionBy("doc_id").orderBy("doc_id"))
    rows = rows.withColumn("__near_copy", once).where("__near_copy = 1").drop("__near_copy")
    return rows.select(docs.columns).union(docs.where("doc_id is null"))


def op2(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"), 3, 85)


OP2_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws
  FROM documents),
s AS (
  SELECT DISTINCT doc_id, g FROM (
    SELECT doc_id, CASE WHEN len(ws) < 3 THEN array_to_string(ws, ' ') ELSE array_to_string(ws[i:i + 2], ' ') END AS g
    FROM (SELECT doc_id, ws, unnest(range(1, greatest(2, len(ws) - 1))) AS i FROM w WHERE len(ws) > 0) t) u),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (
  SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS both_n FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY 1, 2),
e AS (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * both_n >= 85 * (na.n + nb.n - both_n)),
r AS (SELECT doc_id AS node, doc_id AS root FROM documents UNION SELECT e.b, r.root FROM r JOIN e ON e.a = r.node WHERE r.root < e.b)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, c.root AS component_id, c.root = d.doc_id AS kept
FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT node, min(root) AS root FROM r GROUP BY node) c ON c.node = d.doc_id
"""
