"""Quality classifier: a byte-level convolutional network over overlapping chunks of the whole document.

Chunks of CHUNK bytes overlap by half.  Each chunk's max-pooled filter responses give one
logit; a smooth maximum over the chunks' logits of low quality (the mean of exponentials)
combines them into one probability, so a document is judged by all of its text and a
junk passage counts wherever it stands.

Edge cases: a null or empty text is one chunk of padding and gets the network's score of
it.  Repeated rows get equal scores.  Without labelled rows every score is 0.5.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytecnn import ByteCNN, chosen_windows, layout, training_windows
from .common import column, map_batches, slices
from .sampling import bounded_sample, crc_mod
from .wordhash import buffers

CHUNK = 256
TRAIN_ROWS = 4000  # bound of the training sample
TRAIN_CHUNKS = 40  # bound of the chunks of one training text, spread over it: all of 5 KB
STEP_CHUNKS = 10  # of them in an epoch


def smooth_max(z: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """log mean exp of each text's logits, and each logit's weight in it."""
    count = np.diff(first)
    top = np.maximum.reduceat(z, first[:-1])
    e = np.exp(z - np.repeat(top, count))
    total = np.add.reduceat(e, first[:-1])
    return top + np.log(total / count), e / np.repeat(total, count)


class QualityModel:
    def __init__(self, net: ByteCNN | None):
        self.net = net

    def score(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Probability of label 1 of each text of a slice."""
        half = self.net.block
        buf, first = layout(raw, offsets, half)
        m = self.net.pool(buf)
        # chunk j of a text is its blocks j and j + 1; a text of one block is one chunk
        count = np.diff(first)
        last = np.zeros(len(m), dtype=bool)
        last[first[1:] - 1] = count > 1
        at = np.flatnonzero(~last)
        single = np.repeat(count == 1, count)[at]
        z = self.net.head(np.where(single[:, None], m[at], np.maximum(m[at], m[np.minimum(at + 1, len(m) - 1)])))[:, 0].astype(np.float64)
        first = np.concatenate([[0], np.cumsum(np.maximum(count - 1, 1))])
        pooled, _ = smooth_max(z, first)
        return 1 / (1 + np.exp(np.clip(pooled, -30, 30)))


def train(pairs: list[tuple[str, int]], epochs: int = 7, seed: int = 3) -> QualityModel:
    """pairs: (text, quality 0/1)."""
    pairs = [(t or "", int(q)) for t, q in pairs if q is not None]
    raw, offsets = buffers(pa.array([t for t, _ in pairs], pa.large_string()))
    return train_chunks(*training_windows(raw, offsets, CHUNK, TRAIN_CHUNKS), [q for _, q in pairs], epochs, seed)


def train_chunks(win: np.ndarray, own: np.ndarray, labels: list[int], epochs: int = 7, seed: int = 3) -> QualityModel:
    """win: chunks, own: the text of each in order, labels: of the texts.

    An epoch takes STEP_CHUNKS chunks at most of a text, others in each epoch.
    """
    if len(set(labels)) < 2:
        return QualityModel(None)
    low = np.array([1.0 - q for q in labels])
    start = np.searchsorted(own, np.arange(len(labels) + 1))
    net, rng = ByteCNN(12, 1, CHUNK // 2, seed), np.random.default_rng(seed)
    net.p["c"][0] = np.log(max(low.mean(), 1e-3) / max(1 - low.mean(), 1e-3))
    rounds = epochs if len(labels) > 1500 else min(40, epochs * 1500 // max(len(labels), 1))
    for epoch in range(rounds):
        order = rng.permutation(len(labels))
        for at in range(0, len(order), 32):
            i = order[at : at + 32]
            some = [np.arange(start[j], start[j + 1]) for j in i]
            some = [x if len(x) <= STEP_CHUNKS else np.sort(rng.choice(x, STEP_CHUNKS, replace=False)) for x in some]
            take = np.concatenate(some)
            first = np.concatenate([[0], np.cumsum([len(x) for x in some])])

            def loss(z, i=i, first=first):
                pooled, weight = smooth_max(z[:, 0], first)
                d = 1 / (1 + np.exp(-pooled)) - low[i]
                return 0.0, (np.repeat(d, np.diff(first)) * weight / len(i))[:, None].astype(np.float32)

            _, g = net.grads(win[take], loss)
            net.step(g, 0.008 if epoch < rounds - 2 else 0.002)
    return QualityModel(net.trim())


def fit(docs: DataFrame, labels: DataFrame, learn, label: str = "quality") -> QualityModel:
    """Train on chunks of a bounded sample of the labelled rows that may be learned from, spread over the whole of each text."""
    usable = labels.where(learn & F.col(label).isin(0, 1)).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where("doc_id is not null")
    chosen = bounded_sample(usable.distinct(), "doc_id", TRAIN_ROWS)
    if not chosen:
        return QualityModel(None)
    return train_chunks(*chosen_windows(docs, [(r["doc_id"], r["y"]) for r in chosen], "int", CHUNK, TRAIN_CHUNKS))


def score(docs: DataFrame, model: QualityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score) of every row."""

    def run(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        out = np.full(batch.num_rows, 0.5)
        if model.net is not None:
            for a, b in slices(offsets, 2 << 20):
                out[a:b] = model.score(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
        yield pa.RecordBatch.from_arrays([column(batch, "doc_id"), pa.array(out)], names=["doc_id", "score"])

    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return map_batches(src, run, "doc_id long, score double")


def op4(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = fit(docs, labels, crc_mod("doc_id", 3) != 1)
    return score(docs, model).select(
        "doc_id", (crc_mod("doc_id", 3) == 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted")
    )
