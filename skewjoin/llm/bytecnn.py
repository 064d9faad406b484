"""A byte-level convolutional network in numpy: embedding, filters of several widths, max pooling, linear head.

Texts are laid out one after the other in a byte buffer, each padded with zero bytes to
whole blocks (at least WIDTH zeros, so no filter reads into the next text).  A filter's
responses are pooled per block of BLOCK start positions; a window is one block or several
adjacent ones, so overlapping windows share their responses.  The four phases of the
convolution are plain matrix products on views of the embedded buffer, without copies.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column, map_batches, slices
from .wordhash import buffers

WIDTH = 4
EMB = 8
WIDTHS = (2, 3, 4)


def layout(raw: np.ndarray, offsets: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray]:
    """The padded buffer and the n + 1 block offsets of the texts; an empty text has one block of zeros."""
    size = np.diff(offsets)
    blocks = (size + WIDTH + block - 1) // block
    first = np.concatenate([[0], np.cumsum(blocks)])
    out = np.zeros(int(first[-1]) * block, dtype=np.uint8)
    for i in range(len(size)):  # one memory copy per text
        at = first[i] * block
        out[at : at + size[i]] = raw[offsets[i] : offsets[i + 1]]
    return out, first


class ByteCNN:
    def __init__(self, filters: int, classes: int, block: int, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.block, self.filters = block, filters * len(WIDTHS)
        self.p = {
            "E": rng.normal(0, 0.5, (256, EMB)),
            "W": rng.normal(0, 0.35, (WIDTH * EMB, self.filters)),
            "b": np.zeros(self.filters),
            "V": rng.normal(0, 0.2, (self.filters, classes)),
            "c": np.zeros(classes),
        }
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}
        self.mask = np.ones((WIDTH * EMB, self.filters), dtype=np.float32)
        for i, w in enumerate(WIDTHS):
            self.mask[w * EMB :, i * filters : (i + 1) * filters] = 0
        self.p["W"] *= self.mask
        self._adam = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in self.p.items()}
        self._t = 0

    def trim(self) -> "ByteCNN":
        """Drop the optimiser's state before shipping to executors."""
        self._adam = {}
        return self

    def _embed(self, buf: np.ndarray) -> np.ndarray:
        x = np.zeros((len(buf) + WIDTH, EMB), dtype=np.float32)
        np.take(self.p["E"], buf, axis=0, out=x[: len(buf)], mode="clip")
        return x.reshape(-1)

    def _phase(self, x: np.ndarray, n: int, o: int) -> np.ndarray:
        return x[o * EMB : o * EMB + n * EMB].reshape(n // WIDTH, WIDTH * EMB)

    def pool(self, buf: np.ndarray, step: int = 1 << 15) -> np.ndarray:
        """Largest response of every filter in each block, for a whole padded buffer."""
        per = max(1, step // self.block) * self.block
        out = np.empty((len(buf) // self.block, self.filters), dtype=np.float32)
        w = self.p["W"]
        for at in range(0, len(buf), per):
            # the bytes after the step belong to the responses of its last positions
            upto = min(at + per, len(buf))
            n = upto - at
            part = buf[at : upto + WIDTH]
            if len(part) < n + WIDTH:  # behind the last text as behind any other: zero bytes
                part = np.concatenate([part, np.zeros(n + WIDTH - len(part), np.uint8)])
            x = self._embed(part)
            rows = slice(at // self.block, upto // self.block)
            best = None
            for o in range(WIDTH):
                y = (self._phase(x, n, o) @ w).reshape(n // self.block, self.block // WIDTH, self.filters).max(axis=1)
                best = y if best is None else np.maximum(best, y, out=best)
            out[rows] = best
        return out

    def head(self, pooled: np.ndarray) -> np.ndarray:
        return np.maximum(pooled + self.p["b"], 0) @ self.p["V"] + self.p["c"]

    # ---- training ----

    def _forward(self, win: np.ndarray):
        """win: (B, L) bytes with at least WIDTH bytes of context after the L - WIDTH start positions."""
        B, L = win.shape
        n = L - WIDTH
        x = self._embed(win.reshape(-1))
        best = arg = None
        for o in range(WIDTH):
            y = (self._phase(x, B * L, o) @ self.p["W"]).reshape(B, L // WIDTH, self.filters)[:, : n // WIDTH]
            a = y.argmax(axis=1)
            m = np.take_along_axis(y, a[:, None, :], axis=1)[:, 0]
            a = a * WIDTH + o
            if best is None:
                best, arg = m, a
            else:
                up = m > best
                best, arg = np.where(up, m, best), np.where(up, a, arg)
        return x, best, arg

    def grads(self, win: np.ndarray, dlogit):
        """dlogit: function of the windows' logits that returns (loss, gradient of the logits)."""
        B, L = win.shape
        x, best, arg = self._forward(win)
        pre = best + self.p["b"]
        h = np.maximum(pre, 0)
        loss, dz = dlogit(h @ self.p["V"] + self.p["c"])
        g = {"V": h.T @ dz, "c": dz.sum(0)}
        dh = (dz @ self.p["V"].T) * (pre > 0)
        g["b"] = dh.sum(0)
        at = arg + (np.arange(B) * L)[:, None]
        cols = x.reshape(-1, EMB)[at[..., None] + np.arange(WIDTH)].reshape(B, self.filters, WIDTH * EMB)
        g["W"] = np.einsum("bf,bfk->kf", dh, cols) * self.mask
        byte = win.reshape(-1)[np.minimum(at[..., None] + np.arange(WIDTH), win.size - 1)].reshape(-1)
        dx = (dh[..., None] * self.p["W"].T[None]).reshape(-1, EMB)
        g["E"] = np.stack([np.bincount(byte, dx[:, e], 256) for e in range(EMB)], axis=1)
        return loss, g

    def step(self, g: dict, lr: float, decay: float = 1e-4) -> None:
        self._t += 1
        for k, v in self.p.items():
            m, s = self._adam[k]
            d = g[k].astype(np.float32) + decay * v
            m += 0.1 * (d - m)
            s += 0.01 * (d * d - s)
            v -= lr * (m / (1 - 0.9**self._t)) / (np.sqrt(s / (1 - 0.99**self._t)) + 1e-7)


def training_windows(raw: np.ndarray, offsets: np.ndarray, length: int, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(windows, index of their text): up to `most` half-overlapping windows of each text, zero padded.

    If a text has more, they are spread evenly over the whole of it.
    """
    size = np.diff(offsets)
    n = np.maximum(1, -(-size // (length // 2)) - 1)
    take = np.minimum(n, most)
    own = np.repeat(np.arange(len(size)), take)
    j = np.arange(len(own)) - np.repeat(np.cumsum(take) - take, take)
    j = np.rint(j * ((n - 1) / np.maximum(take - 1, 1))[own]).astype(np.int64)
    start = offsets[:-1][own] + j * (length // 2)
    place = start[:, None] + np.arange(length + WIDTH)
    # a window's filters read WIDTH bytes further in scoring too, as far as the text goes
    inside = place < offsets[1:][own][:, None]
    if not len(raw):
        return np.zeros(place.shape, dtype=np.uint8), own
    return np.where(inside, raw[np.minimum(place, len(raw) - 1)], 0).astype(np.uint8), own


def chosen_windows(docs: DataFrame, chosen: list[tuple], label: str, length: int, most: int, id_col: str = "doc_id", text_col: str = "text") -> tuple[np.ndarray, np.ndarray, list]:
    """(windows, index of their text, label of each text) of the chosen rows (id, label), taken from whole texts where they lie.

    chosen is a bounded sample, hence broadcast; what comes back is at most `most` windows a row.
    """
    small = docs.sparkSession.createDataFrame(chosen, f"k long, y {label}")
    rows = docs.select(F.col(id_col).cast("long").alias("k"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).join(F.broadcast(small), "k")

    def cut(batch: pa.RecordBatch):
        raw, offsets = buffers(column(batch, "text"))
        for a, b in slices(offsets):
            win, own = training_windows(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], length, most)
            parts = [win[own == i].tobytes() for i in range(b - a)]
            yield pa.RecordBatch.from_arrays([column(batch, "k").slice(a, b - a), column(batch, "y").slice(a, b - a), pa.array(parts, pa.binary())], names=["k", "y", "w"])

    got = sorted(((r["k"], r["y"], bytes(r["w"])) for r in map_batches(rows, cut, f"k long, y {label}, w binary").collect()))
    width = length + WIDTH
    count = [len(w) // width for _, _, w in got]
    win = np.frombuffer(b"".join(w for _, _, w in got), dtype=np.uint8).reshape(-1, width)
    return win, np.repeat(np.arange(len(got)), count), [y for _, y, _ in got]
