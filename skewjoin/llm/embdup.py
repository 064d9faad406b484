"""Embedding near-duplicates: iterative quantisation, multi-index Hamming tables, exact reranking.

A rotation of the leading principal directions is learned on a bounded sample so that the
signs of the rotated coordinates are balanced binary codes.  Every vector is indexed: its
code is cut into TABLES substrings, and it enters the bucket of each substring and of
all substrings one bit away, so two vectors meet if some substring differs in two bits at
most.  Inside the buckets a maximum spanning forest by the Hamming distance of longer sketches
proposes pairs: signs on SKETCH drawn directions, of which a pair differs in the share of its
angle in a half turn, so that unrelated vectors are never near, however many there are.  With
the codes' few bits chance pairs would join all vectors of a large table in one cluster, whose
components are compared with each other.  Cosines of the original vectors in double precision confirm them, pairs still in
different components follow, and confirmed pairs make the components.  As all links of a
vector lie in its component, links are then counted by products of blocks of a component,
each vector against all others there, without a row per pair.

Edge cases: a vector that is null, empty, zero or holds null or non-finite components has
no links and is its own component.  Vectors of different lengths never link.  Equal vectors
are one class, whose size counts for the links of each.  A null id has a null component.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column, components, hub_join, map_batches, release, stage
from .grouping import block_rows, join_components, open_blocks, open_clusters, propose
from .sampling import bounded_sample

SAMPLE = 4000  # bound of the sample the rotation is learned on
BITS = 64
TABLES = 4
SKETCH = 256  # bits of the sketch by which members of a bucket are compared
MARGIN = 4  # standard deviations of the differing bits of a pair at the threshold, up to which it is reranked
SURE = 5.5 / 64  # share of differing bits up to which a pair is nearly always a link
PAIRWISE = 2048  # buckets up to this size are compared at once
BLOCK = 8192


class Rotation:
    """Mean and projection to BITS coordinates for vectors of one length."""

    def __init__(self, mean: np.ndarray, project: np.ndarray):
        self.mean, self.project = mean, project

    def codes(self, unit: np.ndarray) -> np.ndarray:
        bits = ((unit - self.mean) @ self.project) > 0
        weight = np.uint64(1) << np.arange(bits.shape[1], dtype=np.uint64)
        return (bits * weight).sum(axis=1, dtype=np.uint64)


def _orthogonal(n: int, seed: int) -> np.ndarray:
    return np.linalg.qr(np.random.default_rng(seed).normal(size=(n, n)))[0]


def learn_rotation(unit: np.ndarray, rounds: int = 30, seed: int = 5) -> Rotation:
    """Iterative quantisation: alternate the signs of the rotated data and the rotation nearest to them.

    Vectors of fewer than BITS components get several rotations, from different starts, so that
    every code has BITS bits and its substrings tell vectors apart.
    """
    dim = unit.shape[1]
    bits = min(BITS, dim)
    mean = unit.mean(axis=0) if len(unit) else np.zeros(dim)
    x = unit - mean
    _, _, directions = np.linalg.svd(x if len(x) >= dim else np.vstack([x, np.eye(dim) * 1e-6]), full_matrices=False)
    w = directions[:bits].T
    v = x @ w
    parts = []
    for start in range(-(-BITS // bits)):
        rotation = _orthogonal(bits, seed + start)
        for _ in range(rounds if start == 0 else 3):  # later ones stay near their starts: all would end alike
            signs = np.where(v @ rotation > 0, 1.0, -1.0)
            a, _, b = np.linalg.svd(signs.T @ v)
            rotation = (a @ b).T
        parts.append(w @ rotation)
    return Rotation(mean, np.hstack(parts)[:, :BITS])


def drawn_rotation(dim: int, seed: int = 5) -> Rotation:
    """Directions for a length of vector that no sample holds: drawn, not learned."""
    rng = np.random.default_rng([seed, dim])
    return Rotation(np.zeros(dim), rng.normal(size=(dim, BITS)))


def unit_rows(values: pa.Array) -> tuple[list[np.ndarray], np.ndarray]:
    """(unit vectors of the valid rows, which rows are valid)."""
    values = values.cast(pa.large_list(pa.float64()))
    n = len(values)
    out, valid = [], np.zeros(n, dtype=bool)
    for i, v in enumerate(values):
        x = v.values if v.is_valid else None
        if x is None or len(x) == 0 or x.null_count:
            continue
        x = x.to_numpy(zero_copy_only=False)
        norm = np.sqrt((x * x).sum())
        if np.isfinite(x).all() and np.isfinite(norm) and norm > 0:
            out.append(x / norm)
            valid[i] = True
        elif np.isfinite(x).all() and (big := np.abs(x).max()) > 0:
            y = x / big
            out.append(y / np.sqrt((y * y).sum()))
            valid[i] = True
    return out, valid


def hamming_similarity(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """1 - share of differing bits of (sketch words, length) signatures; different lengths are never similar."""
    differ = np.bitwise_count(a[..., 0] ^ b[..., 0]).astype(np.uint16)
    for k in range(1, a.shape[-1] - 1):  # word by word: a sum over a last axis of four is slow
        differ += np.bitwise_count(a[..., k] ^ b[..., k])
    return np.where(a[..., -1] == b[..., -1], 1 - differ / (64.0 * (a.shape[-1] - 1)), -1.0)


def sketches(unit: np.ndarray, seed: int = 11) -> np.ndarray:
    """(n, SKETCH / 64) words: the signs of unit vectors on drawn directions, the same for all vectors of a length."""
    dim = unit.shape[1]
    bits = unit @ np.random.default_rng([seed, dim]).normal(size=(dim, SKETCH)) > 0
    return np.packbits(bits, axis=1, bitorder="little").view(np.uint64)


def least_similar(least: float) -> float:
    """The share of equal bits below which a pair is left out: one with the cosine `least` has as few
    with a probability of 1 in 30,000."""
    p = np.arccos(min(max(least, -1.0), 1.0)) / np.pi
    return 1 - p - MARGIN * np.sqrt(p * (1 - p) / SKETCH)


def encode(vectors: DataFrame, rotations: dict[int, Rotation]) -> DataFrame:
    """(id, dim, code, unit) of the valid vectors."""

    def run(batch: pa.RecordBatch):
        rows, valid = unit_rows(column(batch, "v"))
        ids = column(batch, "id").to_numpy(zero_copy_only=False)[valid]
        dims = np.array([len(r) for r in rows], dtype=np.int32)
        code = np.zeros(len(rows), dtype=np.uint64)
        for d in np.unique(dims):
            at = np.flatnonzero(dims == d)
            code[at] = (rotations.get(int(d)) or drawn_rotation(int(d))).codes(np.stack([rows[i] for i in at]))
        if len(rows):
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids.astype(np.int64)), pa.array(dims), pa.array(code.view(np.int64)), pa.array([r.tobytes() for r in rows], pa.binary())],
                names=["id", "dim", "code", "unit"],
            )

    return map_batches(vectors, run, "id long, dim int, code long, unit binary")


def fit_rotations(vectors: DataFrame) -> dict[int, Rotation]:
    """A rotation for each length of vector in a bounded sample; other lengths get drawn directions."""
    rows = bounded_sample(vectors.where("v is not null"), "id", SAMPLE)
    by: dict[int, list] = {}
    for r in rows:
        x = r["v"]
        if x and all(y is not None for y in x):
            x = np.asarray(x, dtype=np.float64)
            n = np.sqrt((x * x).sum())
            if np.isfinite(n) and n > 0:
                by.setdefault(len(x), []).append(x / n)
    return {d: learn_rotation(np.stack(x)) for d, x in by.items()}


def bucket_keys(codes: DataFrame) -> DataFrame:
    """(key, id): the buckets of each code's substrings and of those one bit away."""
    width = BITS // TABLES
    rows = []
    for t in range(TABLES):
        sub = F.shiftrightunsigned(F.col("code"), t * width).bitwiseAND(F.lit((1 << width) - 1))
        for flip in [0] + [1 << i for i in range(width)]:
            rows.append(F.xxhash64(F.lit(t), F.col("dim"), sub.bitwiseXOR(F.lit(flip).cast("long"))))
    return codes.select(F.explode(F.array(*rows)).alias("key"), "id")


def confirm(pairs: DataFrame, units: DataFrame, least: float) -> DataFrame:
    """The pairs (a, b) whose vectors have a cosine of at least `least`, in double precision."""
    joined = (
        pairs.join(units.select(F.col("id").alias("a"), F.col("unit").alias("ua")), "a")
        .join(units.select(F.col("id").alias("b"), F.col("unit").alias("ub")), "b")
    )

    def run(batch: pa.RecordBatch):
        ua, ub = column(batch, "ua").to_pylist(), column(batch, "ub").to_pylist()
        cos = np.array([np.dot(np.frombuffer(x), np.frombuffer(y)) if len(x) == len(y) else -1.0 for x, y in zip(ua, ub)])
        ok = pa.array(np.flatnonzero(cos >= least))
        if len(ok):
            yield pa.RecordBatch.from_arrays([column(batch, c).take(ok) for c in ("a", "b")], names=["a", "b"])

    return map_batches(joined.select("a", "b", "ua", "ub"), run, "a long, b long")


def exact(least: float):
    """Functions for join_components: unit vectors of one length, and the exact test."""

    def load(blobs: list[bytes]):
        return np.stack([np.frombuffer(b) for b in blobs])

    def linked(x, i: int, rest: np.ndarray) -> np.ndarray:
        return x[rest] @ x[i] >= least

    return load, linked


def count_links(units: DataFrame, comp: DataFrame, least: float) -> DataFrame:
    """(id, n_links) of the classes in components: links to other vectors, all of which lie in the component.

    A component of n classes is dealt into n / BLOCK blocks; each pair of blocks is one
    group of at most 2 * BLOCK vectors, whose cosines are one matrix product.
    """
    rows = units.join(comp.select(F.col("node").alias("id"), "component"), "id")
    size = comp.groupBy("component").agg(F.count(F.lit(1)).alias("c"))
    n = F.ceil(F.col("c") / BLOCK).cast("int")
    rows = hub_join(rows, size, "component", "c", comp.count()).withColumn("blk", F.pmod(F.xxhash64("id"), n).cast("int"))
    rows = rows.select("component", "id", "m", "unit", "blk", F.explode(F.sequence(F.lit(0), n - 1)).alias("o")).select(
        "component", F.least("blk", "o").alias("i"), F.greatest("blk", "o").alias("j"), "id", "m", "unit", "blk"
    )

    def links(t: pa.Table) -> pa.Table:
        ids, m, blk = (t.column(c).to_numpy() for c in ("id", "m", "blk"))
        x = np.frombuffer(b"".join(t.column("unit").to_pylist())).reshape(len(ids), -1)
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        left, right = np.flatnonzero(blk == i), np.flatnonzero(blk == j)
        out = np.zeros(len(ids), dtype=np.int64)
        for at in range(0, len(left), 512):
            some = left[at : at + 512]
            near = (x[some] @ x[right].T) >= least
            if i == j:
                near &= some[:, None] != right[None]
            out[some] += near @ m[right]
            if i != j:
                out[right] += near.T @ m[some]
        return pa.table({"id": ids, "k": out})

    return rows.groupBy("component", "i", "j").applyInArrow(links, "id long, k long").groupBy("id").agg(F.sum("k").alias("k"))


def near_vectors(vectors: DataFrame, least: float = 0.9, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row."""
    src = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v"))
    named = src.where("id is not null")
    # hashes pass over null elements, so only vectors without any may share a class
    whole = F.col("v").isNotNull() & ~F.exists("v", lambda x: x.isNull())
    digest = [F.xxhash64(F.lit(s), F.size("v"), "v") for s in (1, 2)]
    member = named.select("id", digest[0].alias("h1"), digest[1].alias("h2"), whole.alias("has"))
    classes = member.where("has").groupBy("h1", "h2").agg(F.min("id").alias("class_id"), F.count(F.lit(1)).alias("m"))
    member = stage(member.join(classes.withColumn("has", F.lit(True)), ["h1", "h2", "has"], "left").select("id", F.coalesce("class_id", "id").alias("class_id"), F.coalesce("m", F.lit(1)).alias("m")), "classes")
    reps = member.where("id = class_id").select("id", "m").distinct()
    rotations = fit_rotations(named)
    codes = stage(encode(named.join(reps.select("id"), "id", "left_semi"), rotations).dropDuplicates(["id"]).join(reps, "id"), "codes")
    keyed = bucket_keys(codes).distinct()
    shared = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("c"), F.min("id").alias("lead")).where("c > 1")
    groups = stage(keyed.join(shared, "key"), "groups")
    sigs = stage(_signatures(codes), "sigs")
    cutoff = least_similar(least)
    pairs = stage(propose(block_rows(groups, sigs), hamming_similarity, cutoff, max(cutoff, 1 - SURE), PAIRWISE), "pairs")
    links = stage(confirm(pairs.select("a", "b"), codes, least), "links")
    comp = components(links)
    crossing = open_blocks(groups, sigs, comp)
    if crossing is not None:
        extra = stage(propose(crossing, hamming_similarity, cutoff, max(cutoff, 1 - SURE), PAIRWISE), "pairs")
        links = stage(links.union(confirm(extra.select("a", "b"), codes, least)), "links")
        pairs, comp = pairs.union(extra), components(links)
    clusters = components(pairs)
    units = codes.select("id", F.col("unit").alias("payload"))
    more = stage(join_components(open_clusters(clusters, comp, units, BLOCK), *exact(least)), "links")
    if more.limit(1).count():
        comp = components(links.union(more))
    counts = stage(count_links(codes.select("id", "m", "unit"), comp, least), "counts")
    release(groups, sigs, pairs, links, clusters, more)
    valid = codes.select(F.col("id").alias("class_id"), F.lit(True).alias("valid"))
    out = (
        member.join(comp.withColumnRenamed("node", "class_id"), "class_id", "left")
        .join(counts.withColumnRenamed("id", "class_id"), "class_id", "left")
        .join(valid, "class_id", "left")
    )
    # an invalid vector is alone, even among equals
    alone = F.col("valid").isNull()
    out = out.select(
        F.col("id").alias("vec_id"),
        F.when(alone, F.lit(0)).otherwise(F.coalesce("k", F.lit(0)) + F.col("m") - 1).cast("long").alias("n_links"),
        F.when(alone, F.col("id")).otherwise(F.coalesce("component", "class_id")).alias("component_id"),
    ).withColumn("kept", F.col("vec_id") == F.col("component_id"))
    lost = src.where("id is null").select(F.col("id").alias("vec_id"), F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"), F.lit(True).alias("kept"))
    return out.union(lost)


def _signatures(codes: DataFrame) -> DataFrame:
    """(id, sig): sketch and length as words of 8 bytes."""

    def run(batch: pa.RecordBatch):
        unit, dim = column(batch, "unit").to_pylist(), column(batch, "dim").to_numpy()
        sig = np.empty((len(dim), SKETCH // 64 + 1), dtype=np.uint64)
        sig[:, -1] = dim
        for d in np.unique(dim):
            at = np.flatnonzero(dim == d)
            sig[at, :-1] = sketches(np.frombuffer(b"".join([unit[i] for i in at])).reshape(len(at), d))
        yield pa.RecordBatch.from_arrays([column(batch, "id"), pa.array([r.tobytes() for r in sig], pa.binary())], names=["id", "sig"])

    return map_batches(codes.select("id", "unit", "dim"), run, "id long, sig binary")


def op3(spark, sf_dir: str) -> DataFrame:
    return near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))



OP3_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings
  WHERE len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
l AS (SELECT x.vec_id AS a, y.vec_id AS b FROM v x JOIN v y ON x.vec_id <> y.vec_id AND len(x.e) = len(y.e) WHERE list_cosine_similarity(x.e, y.e) >= 0.9),
r AS (SELECT vec_id AS node, vec_id AS root FROM embeddings UNION SELECT l.b, r.root FROM r JOIN l ON l.a = r.node WHERE r.root < l.b)
SELECT x.vec_id, coalesce(n.n, 0)::BIGINT AS n_links, c.root AS component_id, c.root = x.vec_id AS kept
FROM embeddings x LEFT JOIN (SELECT a, count(*) AS n FROM l GROUP BY a) n ON n.a = x.vec_id JOIN (SELECT node, min(root) AS root FROM r GROUP BY node) c ON c.node = x.vec_id
"""
