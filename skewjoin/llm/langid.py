"""Language identification by a byte convolutional network.

Filters of widths 2 to 4 over byte embeddings, max pooling per fixed-length window and
softmax, trained on labelled texts; a text's language is that of the mean of its windows'
probabilities, each weighted by the bytes it holds.  Every byte of every text is read.

Edge cases: a null text, or one without a letter, is `und` with score 0.  Rows with null
labels are predicted, never learned from.  With no labelled rows every text is `und`.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytecnn import ByteCNN, chosen_windows, layout, training_windows
from .common import column, map_batches, slices
from .sampling import bounded_sample, crc_mod
from .wordhash import buffers

WINDOW = 256
TRAIN_ROWS = 3000  # bound of the training sample
TRAIN_WINDOWS = 4  # bound of the windows of one training text, spread over it
UNDETERMINED = "und"


class LanguageModel:
    def __init__(self, langs: list[str], net: ByteCNN | None):
        self.langs, self.net = langs, net

    def predict(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index of the language, probability) of each text of a slice."""
        buf, first = layout(raw, offsets, WINDOW)
        z = self.net.head(self.net.pool(buf)).astype(np.float64)
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        size, blocks = np.diff(offsets), np.diff(first)
        place = np.arange(len(z)) - np.repeat(first[:-1], blocks)
        weight = np.clip(np.repeat(size, blocks) - place * WINDOW, 1e-9, WINDOW)
        total = np.add.reduceat(p * weight[:, None], first[:-1], axis=0)
        total /= total.sum(axis=1, keepdims=True)
        best = total.argmax(axis=1)
        return best, total[np.arange(len(best)), best]


def train(pairs: list[tuple[str, str]], epochs: int = 6, seed: int = 7) -> LanguageModel:
    """pairs: (text, language). Deterministic for the same pairs and seed."""
    pairs = [(t, y) for t, y in pairs if t and y is not None]
    raw, offsets = buffers(pa.array([t for t, _ in pairs], pa.large_string()))
    return train_windows(*training_windows(raw, offsets, WINDOW, TRAIN_WINDOWS), [y for _, y in pairs], epochs, seed)


def train_windows(win: np.ndarray, own: np.ndarray, labels: list[str], epochs: int = 6, seed: int = 7) -> LanguageModel:
    """win: windows, own: the text of each, labels: of the texts."""
    langs = sorted(set(labels))
    if not langs:
        return LanguageModel([], None)
    label = {y: i for i, y in enumerate(langs)}
    y = np.array([label[l] for l in labels])[own]
    net, rng = ByteCNN(12, len(langs), WINDOW, seed), np.random.default_rng(seed)
    # no class may drown the others: inverse root frequency
    freq = np.bincount(y, minlength=len(langs)) / len(y)
    importance = (1 / np.sqrt(np.maximum(freq, 1e-6)))
    importance /= (importance * freq).sum()
    steps = 0
    for epoch in range(epochs if len(win) > 2000 else epochs * 3):
        order = rng.permutation(len(win))
        for at in range(0, len(order), 128):
            i = order[at : at + 128]

            def loss(z, i=i):
                p = np.exp(z - z.max(1, keepdims=True))
                p /= p.sum(1, keepdims=True)
                k = importance[y[i]][:, None]
                d = p.copy()
                d[np.arange(len(i)), y[i]] -= 1
                return 0.0, (d * k / len(i)).astype(np.float32)

            _, g = net.grads(win[i], loss)
            net.step(g, 0.01 if epoch < epochs - 2 else 0.003)
            steps += 1
    return LanguageModel(langs, net.trim())


def fit(rows: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> LanguageModel:
    """Train on windows of a bounded sample of the rows with a text and a label, spread over the whole of each text."""
    usable = rows.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), F.col(lang_col).cast("string").alias("lang")).where(
        "doc_id is not null and lang is not null and text is not null and length(text) >= 20"
    )
    chosen = bounded_sample(usable.select("doc_id", "lang").distinct(), "doc_id", TRAIN_ROWS)
    if not chosen:
        return LanguageModel([], None)
    return train_windows(*chosen_windows(usable, [(r["doc_id"], r["lang"]) for r in chosen], "string", WINDOW, TRAIN_WINDOWS))


def _predicted(model: LanguageModel, text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(language, score) of each text of a batch."""
    letter = pc.fill_null(pc.match_substring_regex(text, r"\pL"), False).to_numpy(zero_copy_only=False)
    lang = np.full(len(text), UNDETERMINED, dtype=object)
    score = np.zeros(len(text))
    if model.net is not None:
        raw, offsets = buffers(text)
        for a, b in slices(offsets, 2 << 20):
            best, p = model.predict(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
            lang[a:b] = np.array(model.langs, dtype=object)[best]
            score[a:b] = p
    lang[~letter] = UNDETERMINED
    score[~letter] = 0
    return lang, np.clip(score, 0, 1)


def keep_identified(docs: DataFrame, model: LanguageModel, least: float = 0.5, text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, whose language is determined with at least `least` probability."""

    def run(batch: pa.RecordBatch):
        lang, score = _predicted(model, column(batch, text_col))
        keep = (lang != UNDETERMINED) & (score >= least)
        if keep.any():
            yield batch.filter(pa.array(keep))

    return map_batches(docs, run, docs.schema)


def predict(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score) of every row."""

    def run(batch: pa.RecordBatch):
        lang, score = _predicted(model, column(batch, "text"))
        yield pa.RecordBatch.from_arrays([column(batch, "doc_id"), pa.array(lang, pa.string()), pa.array(score)], names=["doc_id", "lang_pred", "score"])

    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return map_batches(src, run, "doc_id long, lang_pred string, score double")


def op1(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(docs.where(crc_mod("doc_id", 5) != 0))
    return predict(docs, model).select("doc_id", (crc_mod("doc_id", 5) == 0).alias("held_out"), "lang_pred", "score")
