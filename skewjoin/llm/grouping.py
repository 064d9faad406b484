"""Candidate pairs inside shared-key groups, without emitting all pairs of a group.

A group's members are compared by packed signatures, and a spanning forest of the similar
pairs goes on: fewer edges than members.  The proposals connect the candidates into
clusters; every similar pair of a group lies inside one cluster.  The likely proposals are
confirmed pair by pair.  Clusters that confirmed links don't hold together yet are then
compared exactly, member by member across components, where the data of a block lie, and
only links that join components come out.

A group over a block's size is cut into blocks, each compared with itself and with the group's
leader, so every member travels once.  Only if confirmed links leave such a group in several
components are its blocks compared pair by pair, as an exact answer needs.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hub_join, released, small_batches

BLOCK = 8192
SMALL = 48  # groups up to this size are compared together, vectorised over groups

Similarity = Callable[[np.ndarray, np.ndarray], np.ndarray]


def _dealt(rows: DataFrame, key: str, size: str, block: int, *keep: str) -> DataFrame:
    """Rows of each key dealt into pairs (i, j) of blocks, sorted by (key, i, j)."""
    n = F.ceil(F.col(size) / block).cast("int")
    rows = rows.withColumn("blk", F.pmod(F.xxhash64("id"), n).cast("int"))
    rows = rows.select(F.col(key).alias("key"), "id", "blk", *keep, F.explode(F.sequence(F.lit(0), n - 1)).alias("o"))
    return (
        rows.select("key", F.least("blk", "o").alias("i"), F.greatest("blk", "o").alias("j"), "id", "blk", *keep)
        .repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "blk", "id")
    )


def block_rows(groups: DataFrame, sigs: DataFrame) -> DataFrame:
    """(key, i, j, id, blk, sig) sorted by block, from groups (key, id, c: members, lead: the smallest) and sigs (id, sig).

    A large group's leader is in each of its blocks.
    """
    n = F.ceil(F.col("c") / BLOCK).cast("int")
    own = F.pmod(F.xxhash64("id"), n).cast("int")
    rows = groups.join(sigs, "id").select(
        "key", "id", "sig", F.explode(F.when(F.col("id") == F.col("lead"), F.sequence(F.lit(0), n - 1)).otherwise(F.array(own))).alias("i")
    )
    rows = rows.select("key", "i", F.col("i").alias("j"), "id", F.col("i").alias("blk"), "sig")
    return rows.repartition("key", "i").sortWithinPartitions("key", "i", "id")


def open_blocks(groups: DataFrame, sigs: DataFrame, comp: DataFrame) -> DataFrame | None:
    """The rows of groups of several blocks that confirmed links leave in several components, dealt into pairs of blocks."""
    large = groups.where(F.col("c") > BLOCK)
    if not large.limit(1).count():
        return None
    named = large.join(comp.select(F.col("node").alias("id"), F.col("component").alias("comp")), "id", "left").withColumn("comp", F.coalesce("comp", "id"))
    parted = named.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count(F.lit(1)).alias("size")).where("lo <> hi")
    rows = hub_join(large, parted.select("key", "size"), "key", "size", large.count())
    return _dealt(rows.join(sigs, "id"), "key", "c", BLOCK, "sig")


def open_clusters(clusters: DataFrame, comp: DataFrame, payload: DataFrame, block: int) -> DataFrame:
    """(key, i, j, id, blk, comp, payload) of the clusters whose members are in several components.

    clusters and comp: (node, component); payload: (id, payload).
    """
    named = clusters.select(F.col("node").alias("id"), F.col("component").alias("cluster")).join(
        comp.select(F.col("node").alias("id"), F.col("component").alias("comp")), "id", "left"
    ).withColumn("comp", F.coalesce("comp", "id"))
    open_ = named.groupBy("cluster").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count(F.lit(1)).alias("c")).where("lo <> hi")
    rows = hub_join(named, open_.select("cluster", "c"), "cluster", "c", clusters.count()).join(payload, "id")
    return _dealt(rows, "cluster", "c", block, "comp", "payload")


def kruskal(a: np.ndarray, b: np.ndarray, s: np.ndarray) -> list[int]:
    """Indices of the edges of a maximum spanning forest."""
    root: dict[int, int] = {}

    def find(x):
        while (y := root.get(x, x)) != x:
            root[x] = x = root.get(y, y)
        return x

    out = []
    for e in np.argsort(-s, kind="stable"):
        x, y = find(int(a[e])), find(int(b[e]))
        if x != y:
            root[x] = y
            out.append(int(e))
    return out


def _prim(sig, similarity, cutoff, sure) -> list[tuple[int, int]]:
    """A spanning forest of a group: a star if all are surely similar to the first, else a maximum one."""
    n = len(sig)
    s = similarity(sig[0], sig[1:])
    if (s >= sure).all():
        return [(0, i) for i in range(1, n)]
    rest, place = sig[1:].copy(), np.arange(1, n)
    best, parent = s.copy(), np.zeros(n - 1, dtype=np.int64)
    out = []
    for k in range(n - 1, 0, -1):
        j = int(best[:k].argmax())
        if best[j] >= cutoff:
            out.append((int(parent[j]), int(place[j])))
        at, mine = int(place[j]), rest[j].copy()
        for x in (rest, place, best, parent):  # the last takes its place
            x[j] = x[k - 1]
        if k > 1:
            s = similarity(mine, rest[: k - 1])
            up = s > best[: k - 1]
            best[: k - 1][up], parent[: k - 1][up] = s[up], at
    return out


def _pairwise(sig, similarity, cutoff, sure) -> list[tuple[int, int]]:
    """The forest of _prim for a group with few similar pairs, from all of its pairs at once; else by _prim."""
    n = len(sig)
    if (similarity(sig[0], sig[1:]) >= sure).all():
        return [(0, i) for i in range(1, n)]
    xs, ys, ss, found, step = [], [], [], 0, max(1, (1 << 16) // n)
    for lo in range(0, n - 1, step):
        s = similarity(sig[lo : lo + step, None], sig[None, lo + 1 :])
        i, j = np.nonzero(s >= cutoff)
        some = j >= i  # column j is member lo + 1 + j
        i, j = i[some], j[some]
        xs.append(lo + i), ys.append(lo + 1 + j), ss.append(s[i, j])
        found += len(i)
        if found > 4 * n:
            return _prim(sig, similarity, cutoff, sure)
    x, y, s = np.concatenate(xs), np.concatenate(ys), np.concatenate(ss)
    return [(int(x[e]), int(y[e])) for e in kruskal(x, y, s)]


def _proposed(ids, sig, cut, similarity, cutoff, sure, pairwise=0):
    """(a, b, similarity) of the forests of consecutive groups with bounds `cut`."""
    size, first = np.diff(cut), cut[:-1]
    group = np.repeat(np.arange(len(size)), size)
    idx = np.flatnonzero(np.repeat((size > 1) & (size <= SMALL), size))
    xs, ys, ss = [], [], []
    for o in range(1, int(size[size <= SMALL].max(initial=1))):
        i = idx[idx + o < len(ids)]
        i = i[(group[i] == group[i + o]) & (ids[i] != ids[i + o])]
        if len(i):
            s = similarity(sig[i], sig[i + o])
            ok = s >= cutoff
            xs.append(i[ok]), ys.append(i[ok] + o), ss.append(s[ok])
    if xs:
        x, y, s = np.concatenate(xs), np.concatenate(ys), np.concatenate(ss)
        order = np.argsort(group[x], kind="stable")
        x, y, s = x[order], y[order], s[order]
        edges = np.concatenate([[0], np.flatnonzero(np.diff(group[x])) + 1, [len(x)]])
        keep = np.ones(len(x), dtype=bool)
        for lo, hi in zip(edges[:-1], edges[1:]):
            if hi - lo > 2:
                keep[lo:hi] = False
                keep[lo + np.array(kruskal(x[lo:hi], y[lo:hi], s[lo:hi]))] = True
        xs, ys, ss = [x[keep]], [y[keep]], [s[keep]]
    for f, n in zip(first[size > SMALL], size[size > SMALL]):
        if pairs := (_pairwise if n <= pairwise else _prim)(sig[f : f + n], similarity, cutoff, sure):
            p = np.array(pairs) + f
            xs.append(p[:, 0]), ys.append(p[:, 1]), ss.append(similarity(sig[p[:, 0]], sig[p[:, 1]]))
    if not xs:
        return np.zeros((2, 0), np.int64), np.zeros(0)
    a, b, s = ids[np.concatenate(xs)], ids[np.concatenate(ys)], np.concatenate(ss)
    p, at = np.unique(np.stack([np.maximum(a, b), np.minimum(a, b)]), axis=1, return_index=True)
    ok = p[0] != p[1]
    return p[:, ok], s[at[ok]]


def _bounds(t: pa.Table) -> np.ndarray:
    key = np.stack([t.column(c).to_numpy() for c in ("key", "i", "j")])
    return np.flatnonzero(np.concatenate([[True], (key[:, 1:] != key[:, :-1]).any(axis=0), [True]]))


def _whole_groups(batches):
    """Tables of whole groups from sorted batches; the last group of a batch may go on in the next."""
    carry = None
    for batch in batches:
        t = pa.Table.from_batches([batch])
        if carry is not None:
            t = pa.concat_tables([carry, t]).combine_chunks()
        if not t.num_rows:
            continue
        last = int(_bounds(t)[-2])
        carry = t.slice(last)
        if last:
            yield t.slice(0, last).combine_chunks()
    if carry is not None and carry.num_rows:
        yield carry.combine_chunks()


def propose(rows: DataFrame, similarity: Similarity, cutoff: float, sure: float, pairwise: int = 0) -> DataFrame:
    """Distinct (a, b, s), a > b, of the forests of the groups of block_rows: pairs with a similarity of `cutoff` at least.

    pairwise: groups up to this size are compared at once, which is faster where few members are similar.
    """

    def run(batches):
        for t in _whole_groups(batches):
            ids = t.column("id").to_numpy()
            sig = np.frombuffer(b"".join(t.column("sig").to_pylist()), dtype=np.uint64).reshape(len(ids), -1)
            p, s = _proposed(ids, sig, _bounds(t), similarity, cutoff, sure, pairwise)
            if p.shape[1]:
                yield pa.RecordBatch.from_arrays([pa.array(p[0]), pa.array(p[1]), pa.array(s.astype(np.float64))], names=["a", "b", "s"])

    small_batches(rows.sparkSession)
    return rows.mapInArrow(released(run), "a long, b long, s double").dropDuplicates(["a", "b"])


def join_components(rows: DataFrame, load: Callable, linked: Callable) -> DataFrame:
    """(a, b): links that join components inside open clusters, at most one less than the components of a group.

    load(payloads) prepares the members of a table of groups; linked(data, i, rest) says
    which of the members `rest` are linked with member i, exactly.
    """

    def run(batches):
        for t in _whole_groups(batches):
            ids, comp, blk = (t.column(c).to_numpy() for c in ("id", "comp", "blk"))
            cut = _bounds(t)
            out_a, out_b = [], []
            for lo, hi in zip(cut[:-1], cut[1:]):
                if hi - lo < 2 or (comp[lo:hi] == comp[lo]).all():
                    continue
                data = load(t.column("payload").slice(lo, hi - lo).to_pylist())
                now, part = comp[lo:hi].copy(), blk[lo:hi]
                across = part[0] != part[-1]
                for i in range(hi - lo - 1):
                    rest = np.arange(i + 1, hi - lo)
                    rest = rest[now[rest] != now[i]]
                    if across:  # pairs inside a block are met in the block's own group
                        rest = rest[part[rest] != part[i]]
                    if not len(rest):
                        continue
                    for j in rest[linked(data, i, rest)]:
                        if now[j] != now[i]:
                            out_a.append(ids[lo + i]), out_b.append(ids[lo + j])
                            now[now == now[j]] = now[i]
            if out_a:
                yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], names=["a", "b"])

    small_batches(rows.sparkSession)
    return rows.mapInArrow(released(run), "a long, b long").distinct()
