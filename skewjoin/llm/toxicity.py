"""Toxicity by class-conditional Kneser-Ney language models.

One bigram model per class over letter words, counted in Spark over the whole texts of all
labelled rows.  A bigram counts once a document, so a word's count is the number of its
contexts, document by document; of near copies with one label each weighs its share, so
that a group of them counts as one text.

The probability of a word in a class is its discounted count there plus the discounted
mass spread by the counts that both classes share:

    p(w)     = max(N(w) - D(w), 0) / n      + lambda    * shared(w)
    p(w | v) = max(N(vw) - D(vw), 0) / c(v) + lambda(v) * p(w)

The discount takes what the shared counts explain: the count expected if both classes used
the word alike, some standard errors and a half more, and at the least TIMES what the other
class's rate gives.  How many standard errors is chosen on the calibration sample.  A rare or an ordinary word is thus left to the shared counts, in both classes
alike, and doesn't tell them apart.  A text's evidence is its log-likelihood under the toxic
model minus that under the ordinary one, divided by its length, for the whole text and for its
most toxic passage; a logistic fit on a bounded sample of whole texts, which the models it
judges have not seen, turns the two into a probability.

Words and bigrams that are counted less than LEAST times in either class are left to the shared
counts.  Of all others Spark finds those that may have something left after their discount; they
are sent to the texts, with no bound on their number.

Edge cases: a null text or one without letters has no evidence and gets the prior.
Repeated rows get equal scores.  Without labelled rows of both classes every score is 0.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import column, hub_join, map_batches, release, slices, stage
from .sampling import bounded_sample, crc_mod
from .wordhash import NOT_LETTER, Words, buffers, mix64, spans_hash, windows

TRAIN_ROWS = {0: 6000, 1: 3000}  # bound of the calibration sample of each class; the counts have none
PASSAGE = 24  # words of a passage
BROADCAST_ROWS = 2_000_000  # up to so many labelled ids are sent to the texts; beyond, both sides are shuffled
LEAST = 2.0
ERRORS, TIMES = (2.5, 3.5), 4.0  # standard errors tried
_BOS, _TOTAL = np.uint64(0x1234567), np.uint64(0x7654321)
UNIT = 1 << 20  # a text's weight, so that counts are whole numbers and reruns agree
#: Columns of counts: of class 0 and 1, in texts that fit the models and in those held back for calibration.
PARTS = ("f0", "f1", "h0", "h1")


def _pair(v: np.ndarray, w: np.ndarray) -> np.ndarray:
    return mix64(v * np.uint64(0x9E3779B97F4A7C15) + w, 3)


def _tokens(raw: np.ndarray, offsets: np.ndarray):
    """(word, its predecessor or the start of the text) of all words, and each text's first."""
    words = Words(raw, offsets, lower=True, gap=NOT_LETTER)
    w = words.hashes()
    v = np.empty_like(w)
    if len(w):
        v[1:] = w[:-1]
        starts = words.first[:-1][words.counts() > 0]
        v[starts] = _BOS
    return w, v, words.first


def document_bigrams(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text index, v, w) of the bigrams of each text, once each."""
    w, v, first = _tokens(raw, offsets)
    own = np.repeat(np.arange(len(offsets) - 1), np.diff(first))
    _, at = np.unique(mix64(_pair(v, w) ^ mix64(own.astype(np.uint64), 71), 72), return_index=True)
    return own[at], v[at], w[at]


def _sums(key: np.ndarray, part: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(distinct keys, a row of sums over PARTS for each)."""
    keys, index = np.unique(key, return_inverse=True)
    return keys, np.bincount(index * len(PARTS) + part, weight, len(keys) * len(PARTS)).reshape(-1, len(PARTS))


def discounted(count: np.ndarray, pooled: np.ndarray, share: float | np.ndarray, other: np.ndarray, errors: float) -> np.ndarray:
    """What is left of counts after their discount.

    pooled: expected if the classes were alike, share: this class's share of all counts,
    other: expected by the other class's rate.
    """
    explained = np.maximum(0.5 + pooled + errors * np.sqrt(pooled * (1 - share)), TIMES * other)
    return np.maximum(count - explained, 0)


class Counts:
    """Counts of the words and bigrams that may tell the classes apart; totals of all."""

    def __init__(self, words: np.ndarray, n: np.ndarray, c: np.ndarray, total: np.ndarray, pairs: tuple[np.ndarray, np.ndarray], b: np.ndarray):
        """words: hashes; n, c: their counts as word and as context, a column of each class; total: of all words.

        pairs: (v, w); b: their counts, a column of each class.
        """
        order = np.argsort(words)
        self.vocab, self.n, self.c, self.total = words[order], n[order], c[order], total
        known = np.isin(pairs[0], self.vocab) & np.isin(pairs[1], self.vocab)
        self.v, self.w, self.b = pairs[0][known], pairs[1][known], b[known]


class KneserNey:
    """Log-likelihood ratios of words and bigrams of two classes, looked up by hash.

    Only words and bigrams whose discounted counts aren't 0 are kept: `base` is the ratio of all others.
    """

    def __init__(self, counts: Counts, errors: float):
        self.errors = errors
        n, total = counts.n, np.maximum(counts.total, 1e-9)
        shared = n.sum(axis=1) / total.sum()
        share = total / total.sum()
        left = np.stack([discounted(n[:, k], total[k] * shared, share[k], n[:, 1 - k] * total[k] / total[1 - k], errors) for k in (0, 1)], axis=1)
        lam = 1 - left.sum(axis=0) / total
        p = left / total + lam * shared[:, None]
        self.base = float(np.log(lam[1]) - np.log(lam[0]))
        told = left.any(axis=1)
        self.vocab = counts.vocab[told]
        self.uni = (np.log(p[told, 1]) - np.log(p[told, 0])).astype(np.float32)
        # bigrams: explained by the pooled bigram, or by the word alone
        vi, wi = np.searchsorted(counts.vocab, counts.v), np.searchsorted(counts.vocab, counts.w)
        c = np.maximum(counts.c[vi], 1e-9)
        pooled = counts.b.sum(axis=1) / c.sum(axis=1)
        own = c / c.sum(axis=1, keepdims=True)
        rest = np.stack([
            discounted(counts.b[:, k], c[:, k] * np.maximum(pooled, p[wi, k]), own[:, k], np.maximum(counts.b[:, 1 - k] * c[:, k] / c[:, 1 - k], c[:, k] * p[wi, k]), errors)
            for k in (0, 1)
        ], axis=1)
        used = np.stack([np.bincount(vi, rest[:, k], len(counts.vocab)) for k in (0, 1)], axis=1) / np.maximum(counts.c, 1e-9)
        lam2 = 1 - np.clip(used, 0, 0.999)
        context = used.any(axis=1)
        self.contexts = counts.vocab[context]
        self.ctx = (np.log(lam2[context, 1]) - np.log(lam2[context, 0])).astype(np.float32)
        told = rest.any(axis=1)
        q = rest[told] / c[told] + lam2[vi[told]] * p[wi[told]]
        pair = _pair(counts.v[told], counts.w[told])
        order = np.argsort(pair)
        self.pair, self.pair_llr = pair[order], (np.log(q[order, 1]) - np.log(q[order, 0])).astype(np.float32)

    def llr(self, w: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Log-likelihood ratio of each word after its predecessor."""

        def look(table, values, key, other):
            if not len(table):
                return np.full(len(key), other, dtype=np.float32)
            i = np.minimum(np.searchsorted(table, key), len(table) - 1)
            return np.where(table[i] == key, values[i], np.float32(other))

        out = look(self.vocab, self.uni, w, self.base) + look(self.contexts, self.ctx, v, 0.0)
        if len(self.pair):
            whole = look(self.pair, self.pair_llr, _pair(v, w), np.nan)
            out = np.where(np.isnan(whole), out, whole)
        return out


def evidence(model: KneserNey, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """(n, 3): length-normalised evidence of the text and of its most toxic passage, both as signed roots of
    what they have over a text of ordinary words; whether it has words."""
    w, v, first = _tokens(raw, offsets)
    x = model.llr(w, v).astype(np.float64) - model.base
    n = np.diff(first)
    total = np.concatenate([[0], np.cumsum(x)])
    out = np.zeros((len(n), 3))
    has = n > 0
    out[:, 0] = np.where(has, (total[first[1:]] - total[first[:-1]]) / np.maximum(n, 1), 0)
    if len(x):
        last = np.repeat(first[1:], n)
        end = np.minimum(np.arange(len(x)) + PASSAGE, last)
        # a passage is PASSAGE words; a shorter text is one passage, scaled by its own length
        size = np.minimum(PASSAGE, np.repeat(n, n))
        full = (end - np.arange(len(x))) >= size
        s = np.where(full, (total[end] - total[np.arange(len(x))]) / np.sqrt(size * PASSAGE), -np.inf)
        out[has, 1] = np.maximum.reduceat(s, first[:-1][has])
    out[:, :2] = np.sign(out[:, :2]) * np.sqrt(np.where(np.abs(out[:, :2]) < 1e-9, 0, np.abs(out[:, :2])))
    out[:, 2] = has
    return out


class ToxicityModel:
    def __init__(self, kn: KneserNey | None, weights: np.ndarray | None, prior: float):
        self.kn, self.weights, self.prior = kn, weights, prior

    def score(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        if self.kn is None:
            return np.zeros(len(offsets) - 1)
        e = evidence(self.kn, raw, offsets)
        z = e[:, :2] @ self.weights[:2] + self.weights[2]
        z = np.where(e[:, 2] > 0, z, 0) + np.log(self.prior / (1 - self.prior))
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _no_model() -> ToxicityModel:
    return ToxicityModel(None, None, 0.0)


def copy_keys(raw: np.ndarray, offsets: np.ndarray) -> list[list[int]]:
    """Keys of each text that near copies share: minima of its shingles, or a short text's own hash."""
    words = Words(raw, offsets, lower=True)
    sh, inside = windows(words.hashes(), words.first, 5)
    sh = np.where(inside, sh, np.uint64(0xFFFFFFFFFFFFFFFF))
    whole = spans_hash(raw, offsets[:-1], offsets[1:])
    out = []
    for i in range(len(offsets) - 1):
        own = sh[words.first[i] : words.first[i + 1]]
        keys = [mix64(mix64(own, 50 + k).min(), 60 + k) for k in range(4)] if len(own) >= 5 else [mix64(whole[i], 64)]
        out.append([int(k) for k in keys])
    return out


def _logistic(x: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
    """(log loss, weights) of a class-balanced logistic fit."""
    a = np.column_stack([x, np.ones(len(x))])
    balance = np.where(y == 1, 0.5 / max(y.mean(), 1e-6), 0.5 / max(1 - y.mean(), 1e-6))
    wts = np.zeros(a.shape[1])
    ridge = np.diag([1e-4] * x.shape[1] + [1e-6]) * len(y)
    for _ in range(80):  # Newton steps
        p = 1 / (1 + np.exp(-np.clip(a @ wts, -30, 30)))
        g = a.T @ (balance * (p - y)) + ridge @ wts
        h = (a * (balance * np.maximum(p * (1 - p), 1e-6))[:, None]).T @ a + ridge
        move = np.clip(np.linalg.solve(h, g), -5, 5)
        wts -= move
        if np.abs(move).max() < 1e-7:
            break
    p = np.clip(1 / (1 + np.exp(-np.clip(a @ wts, -30, 30))), 1e-9, 1 - 1e-9)
    return float(-(balance * (y * np.log(p) + (1 - y) * np.log(1 - p))).mean()), wts


def train(pairs: list[tuple[str, int]], prior: float) -> ToxicityModel:
    """A model of texts in memory, (text, toxic 0/1): a third of each class calibrates. prior: share of toxic texts."""
    pairs = [(t, int(y)) for t, y in pairs if t]
    if len({y for _, y in pairs}) < 2:
        return _no_model()
    raw, offsets = buffers(pa.array([t for t, _ in pairs], pa.large_string()))
    y = np.array([k for _, k in pairs])
    place = np.empty(len(y), dtype=np.int64)
    for k in (0, 1):
        place[y == k] = np.arange((y == k).sum())
    held = (place % 3 == 0) & (np.bincount(y, minlength=2)[y] >= 3)
    own, v, w = document_bigrams(raw, offsets)
    part = (y + 2 * held)[own]
    one = np.ones(len(own))
    words, n = _sums(w, part, one)
    c = np.zeros_like(n)
    heads, h = _sums(v, part, one)
    at = np.minimum(np.searchsorted(words, heads), len(words) - 1)
    c[at[words[at] == heads]] = h[words[at] == heads]
    pair, first = np.unique(_pair(v, w), return_index=True)
    _, b = _sums(_pair(v, w), part, one)

    def counts(mix) -> Counts:
        return Counts(words, n @ mix, c @ mix, (n @ mix).sum(axis=0), (v[first], w[first]), b @ mix)

    some = held if all((held & (y == k)).any() and (~held & (y == k)).any() for k in (0, 1)) else np.ones(len(y), bool)
    fitted = counts(_FIT if some is held else _ALL)
    tried = {e: evidence(KneserNey(fitted, e), raw, offsets)[some, :2] for e in ERRORS}
    errors, weights = _best(tried, y[some].astype(float))
    return ToxicityModel(KneserNey(counts(_ALL), errors), weights, min(max(prior, 1e-4), 1 - 1e-4))


def _best(tried: dict, y: np.ndarray) -> tuple[float, np.ndarray]:
    """(standard errors, weights) of the least loss."""
    fits = {e: _logistic(x, y) for e, x in tried.items()}
    errors = min(fits, key=lambda e: fits[e][0])
    return errors, fits[errors][1]


#: From PARTS to the classes: of the texts that fit, and of all.
_FIT = np.array([[1, 0], [0, 1], [0, 0], [0, 0]], dtype=np.float64)
_ALL = np.array([[1, 0], [0, 1], [1, 0], [0, 1]], dtype=np.float64)


def _ids(rows: DataFrame) -> DataFrame:
    return F.broadcast(rows) if rows.count() <= BROADCAST_ROWS else rows


def learned(docs: DataFrame, labels: DataFrame, learn) -> DataFrame:
    """(doc_id, y, text) of the labelled rows that may be learned from, whole."""
    ids = labels.where(learn & F.col("toxic").isin(0, 1)).select("doc_id", F.col("toxic").cast("int").alias("y")).distinct()
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).where("text <> ''").join(_ids(ids), "doc_id")


def copy_groups(rows: DataFrame) -> DataFrame:
    """(doc_id, y, g, weight, held) of the labelled texts.

    g: the smallest id that shares a copy key; weight: UNIT over the texts of the group and label;
    held: the side of the split, the same for a whole group.
    """

    def run(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        keys = [np.array(k, dtype=np.uint64).view(np.int64) for a, b in slices(offsets) for k in copy_keys(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])]
        yield pa.RecordBatch.from_arrays([column(batch, "doc_id"), column(batch, "y"), pa.array(keys, pa.list_(pa.int64()))], names=["doc_id", "y", "keys"])

    keys = map_batches(rows.select(F.col("doc_id").cast("long").alias("doc_id"), "y", "text"), run, "doc_id long, y int, keys array<long>")
    keys = stage(keys, "keys")
    each = keys.select("doc_id", F.explode("keys").alias("key")).distinct()
    first = each.groupBy("key").agg(F.min("doc_id").alias("g"))
    group = each.join(first, "key").groupBy("doc_id").agg(F.min("g").alias("g"))
    member = keys.groupBy("doc_id", "y").agg(F.count(F.lit(1)).alias("n")).join(group, "doc_id")
    member = member.withColumn("gy", 2 * F.col("g") + F.col("y"))
    size = member.groupBy("gy").agg(F.sum("n").alias("m"))
    held = F.pmod(F.xxhash64(F.lit("held"), "g"), F.lit(3)) == 0
    return stage(hub_join(member, size, "gy", "m", keys.count()).select("doc_id", "y", "g", F.greatest(F.lit(1), F.round(F.lit(UNIT) / F.col("m"))).cast("long").alias("weight"), held.alias("held")), "weights")


def _counted(rows: DataFrame, bigrams: bool = False) -> DataFrame:
    """Sums over PARTS of the weights of documents, as whole numbers.

    (k, n_*, c_*) of every word k, as a word and as a context, and of all words under _TOTAL; or (v, w, n_*) of every bigram.
    """

    def run(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        code, weight = (column(batch, c).to_numpy(zero_copy_only=False) for c in ("code", "weight"))
        for a, b in slices(offsets, 4 << 20):
            own, v, w = document_bigrams(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
            part, share = code[a:b][own], weight[a:b][own]
            if bigrams:
                _, first = np.unique(pair := _pair(v, w), return_index=True)
                _, sums = _sums(pair, part, share)
                keys = [v[first], w[first]]
            else:
                none = np.zeros(len(w))
                key = np.concatenate([w, v, np.full(len(w), _TOTAL)])
                part = np.tile(part, 3)
                key_, n = _sums(key, part, np.concatenate([share, none, share]))
                _, c = _sums(key, part, np.concatenate([none, share, none]))
                keys, sums = [key_], np.hstack([n, c])
            for lo in range(0, len(sums), 20_000):  # small batches: Spark holds them outside its heap
                some = slice(lo, lo + 20_000)
                yield pa.RecordBatch.from_arrays([*[pa.array(x[some].view(np.int64)) for x in keys], *[pa.array(x) for x in sums[some].T.astype(np.int64)]], names=names)

    src = rows.select("text", "weight", (F.col("y") + F.when(F.col("held"), 2).otherwise(0)).cast("int").alias("code"))
    by = ["v", "w"] if bigrams else ["k"]
    sums = [f"n_{p}" for p in PARTS] + ([] if bigrams else [f"c_{p}" for p in PARTS])
    names = [*by, *sums]
    counts = map_batches(src, run, ", ".join(f"{c} long" for c in names))
    return counts.groupBy(*by).agg(*[F.sum(c).alias(c) for c in sums])


def _telling(kind: str, of: list, mixes: list[np.ndarray]) -> Column:
    """Whether a count in columns `kind`_* may be left over after its discount, in a class, under one of the mixes.

    of: for each mix what the counts of the two classes are shares of, as columns.  The least discount
    is taken: the fewest standard errors tried, and for bigrams what the word alone explains left out.
    """
    out = F.lit(False)
    for mix, whole in zip(mixes, of):
        n = [sum((F.col(f"{kind}_{p}") for p, used in zip(PARTS, mix[:, k]) if used), F.lit(0)) / UNIT for k in (0, 1)]
        for k in (0, 1):
            mine, other = (F.greatest(x, F.lit(1e-9)) for x in (whole[k], whole[1 - k]))
            share = mine / (mine + other)
            pooled = (n[0] + n[1]) * share
            out = out | ((n[k] >= 0.5 + pooled + min(ERRORS) * F.sqrt(pooled * (1 - share)) - 1e-6) & (n[k] >= TIMES * n[1 - k] * mine / other - 1e-6))
    return out


def _arrow(rows: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(keys, counts of texts) of a frame that the driver holds."""
    t = rows.toArrow()
    got = [t.column(i).to_numpy().astype(np.int64) for i in range(t.num_columns)]
    return got[0].view(np.uint64), np.stack(got[1:], axis=1) / UNIT


def counted(rows: DataFrame):
    """(words, n, c, totals, (v, w), b) over PARTS, of labelled rows (text, y, weight, held).

    Of the words and bigrams counted LEAST times in a class, those that may tell the classes apart, and the
    words of such bigrams: all others have nothing left after their discount, whatever their number.
    """
    words = stage(_counted(rows), "words")
    _, total = _arrow(words.where(F.col("k") == int(_TOTAL)).select("k", *[f"n_{p}" for p in PARTS]))
    total = total.sum(axis=0)
    mixes = [m for m in (_FIT, _ALL) if (total @ m).all()] or [_ALL]
    often = " or ".join(f"n_f{k} + n_h{k} >= {int(LEAST * UNIT)}" for k in (0, 1))
    known = words.where(often).where(F.col("k") != int(_TOTAL))
    contexts = known.select(F.col("k").alias("v"), *[f"c_{p}" for p in PARTS])
    # the words of a bigram that is frequent enough are so too, but for the start of a text
    of = [[sum((F.col(f"c_{p}") for p, used in zip(PARTS, m[:, k]) if used), F.lit(0)) / UNIT for k in (0, 1)] for m in mixes]
    both = _counted(rows, True).where(often).join(contexts, "v").where(_telling("n", of, mixes)).select("v", "w", *[f"n_{p}" for p in PARTS])
    both = stage(both, "bigrams")
    told = known.where(_telling("n", [[F.lit(float(x)) for x in total @ m] for m in mixes], mixes)).select("k")
    used = told.union(both.select("v")).union(both.select("w")).distinct()
    w, sums = _arrow(known.join(used, "k", "left_semi"))
    order = np.argsort(w)
    w, sums = w[order], sums[order]
    table = both.toArrow()
    v, second = (table.column(c).to_numpy().view(np.uint64) for c in ("v", "w"))
    b = np.stack([table.column(f"n_{p}").to_numpy() for p in PARTS], axis=1) / UNIT
    release(words, both)
    return w, sums[:, :4], sums[:, 4:], total, (v, second), b


def calibrate(rows: DataFrame, chosen: list, counts: Counts) -> tuple[float, np.ndarray]:
    """(standard errors, weights) fitted on the whole texts of the chosen rows, read where they lie."""
    models = [KneserNey(counts, e) for e in ERRORS]

    def run(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        for a, b in slices(offsets):
            part, off = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
            e = np.concatenate([evidence(m, part, off)[:, :2] for m in models], axis=1)
            yield pa.RecordBatch.from_arrays([column(batch, "doc_id").slice(a, b - a), column(batch, "y").slice(a, b - a), pa.array(list(e), pa.list_(pa.float64()))], names=["doc_id", "y", "e"])

    small = rows.sparkSession.createDataFrame([(r["doc_id"], r["y"]) for r in chosen], "doc_id long, y int")
    got = map_batches(rows.join(F.broadcast(small), ["doc_id", "y"], "left_semi").select("doc_id", "y", "text"), run, "doc_id long, y int, e array<double>").collect()
    got.sort(key=lambda r: (r["doc_id"], r["y"], r["e"]))
    e, y = np.array([r["e"] for r in got]), np.array([r["y"] for r in got], dtype=np.float64)
    return _best({k: e[:, 2 * i : 2 * i + 2] for i, k in enumerate(ERRORS)}, y)


def fit(docs: DataFrame, labels: DataFrame, learn) -> ToxicityModel:
    """Models counted over all labelled rows that may be learned from; a bounded sample calibrates them."""
    share = labels.where(learn).agg(F.avg(F.col("toxic").cast("double"))).first()[0]
    groups = copy_groups(learned(docs, labels, learn))
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text")).where("text <> ''").join(_ids(groups), "doc_id")
    sides = {(r["y"], r["held"]) for r in groups.select("y", "held").distinct().collect()}
    if len({y for y, _ in sides}) < 2:
        return _no_model()
    w, n, c, total, pairs, b = counted(rows)
    split = len(sides) == 4  # with too few texts for a split, the same ones fit and calibrate
    heads = groups.where((F.col("doc_id") == F.col("g")) & (F.col("held") if split else F.lit(True))).select("doc_id", "y").distinct()
    chosen = [r for y in (0, 1) for r in bounded_sample(heads.where(F.col("y") == y), "doc_id", TRAIN_ROWS[y])]
    if len({r["y"] for r in chosen}) < 2 or not (total @ _ALL).all():
        return _no_model()

    def counts(mix) -> Counts:
        return Counts(w, n @ mix, c @ mix, total @ mix, pairs, b @ mix)

    errors, weights = calibrate(rows, chosen, counts(_FIT if split else _ALL))
    return ToxicityModel(KneserNey(counts(_ALL), errors), weights, min(max(share or 0.0, 1e-4), 1 - 1e-4))


def score(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score) of every row."""

    def run(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        parts = [model.score(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in slices(offsets)]
        yield pa.RecordBatch.from_arrays([column(batch, "doc_id"), pa.array(np.concatenate(parts))], names=["doc_id", "score"])

    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return map_batches(src, run, "doc_id long, score double")


def op7(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = fit(docs, labels, crc_mod("doc_id", 4) != 2)
    return score(docs, model).select(
        "doc_id", (crc_mod("doc_id", 4) == 2).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted")
    )
