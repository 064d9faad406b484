"""SentencePiece encoding and decoding with seeded merge dropout.

A public BPE vocabulary with scores and byte fallback is read, never trained.  Text gets
the usual leading space and spaces become the space mark; as no piece reaches over the end
of a word, words are encoded one by one.  Each word keeps an agenda of candidate merges,
best score first, leftmost among equals; the candidate that comes up t-th is skipped if a
keyed hash of seed, document, place of the word in the document and t falls under
`dropout` (in steps of 1 / 65536), and a merge puts its new neighbours on the agenda.  So
every occurrence of a word draws its own segmentation, the pieces stay results of merges,
and a rerun agrees.  Rows that share an id and a text share their segmentation.

What an agenda does depends only on the word and on which of its candidates are skipped.
So each word is the root of a tree: a node is a set of skipped places, and holds the
pieces; an occurrence walks from the root along its own skips, which for most ends at the
root or a step below.  Nodes are made once for a task, all new ones of a slice together,
in lockstep in numpy; a task forgets its nodes when there are more than NODES.

Decoding is lossless for every text: characters outside the vocabulary, and literal space
marks, are spelled in bytes.  Every text is decoded and compared after encoding.

Words of more than LOCKSTEP characters may meet more candidates than a node has bits; each
occurrence of such a word runs through a heap.  Both give equal results.

Edge cases: a null or empty text has no pieces (a null decodes to null); a null id draws as 0.
"""

from __future__ import annotations

import hashlib
import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column, map_batches, released, slices, small_batches
from .wordhash import buffers, mix64, spans_hash

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
DROPOUT = 0.1
SEED = 11
LOCKSTEP = 22  # at most 3 * (characters - 1) candidates come up: 63 bits
NODES = 800_000  # remembered by a task
_LANES = 4  # decisions of one hash
MARK, LITERAL_MARK = "▁", "\udc81"  # a lone surrogate can't occur in a text
_NONE = np.int32(2**31 - 1)


SLOT_BITS = 19


def _slot(key: np.ndarray) -> np.ndarray:
    return ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - SLOT_BITS)).astype(np.int64)


class Vocabulary:
    """Pieces, byte pieces and the table of merges (left, right) -> piece of a BPE model."""

    def __init__(self, pieces: list[str], scores: list[float], bytes_: dict[int, int], normal: list[bool]):
        self.bytes_ = [bytes_[b] for b in range(256)]
        self.id = {p: i for i, p in enumerate(pieces) if normal[i]}
        order = sorted(set(-scores[i] for i in self.id.values()))
        rank = {s: k for k, s in enumerate(order)}
        keys, merged, ranks = [], [], []
        for p, i in self.id.items():
            for cut in range(1, len(p)):
                a, b = self.id.get(p[:cut]), self.id.get(p[cut:])
                if a is not None and b is not None:
                    keys.append((a << 20) | b)
                    merged.append(i)
                    ranks.append(rank[-scores[i]])
        by = np.argsort(np.array(keys, dtype=np.int64))
        self.keys = np.array(keys, dtype=np.int64)[by]
        self.merged = np.array(merged, dtype=np.int32)[by]
        self.ranks = np.array(ranks, dtype=np.int32)[by]
        self.slots: tuple | None = None
        multi = "".join(p for p in self.id if len(p) > 1)
        # white space that no longer piece holds is a word of its own
        self.apart = np.zeros(256, dtype=bool)
        self.apart[[ord(c) for c in "\t\n\u000b\f\r" if c not in multi]] = True
        if any(MARK in p.lstrip(MARK) for p in self.id):
            raise ValueError("a piece reaches over the end of a word")
        back = {v: k for k, v in bytes_.items()}
        spelled = [bytes([back[i]]) if i in back else p.replace(MARK, " ").encode("utf-8", "surrogatepass") if normal[i] else b"" for i, p in enumerate(pieces)]
        self.size = np.array([len(s) for s in spelled], dtype=np.int64)
        self.at = np.cumsum(self.size) - self.size
        self.blob = np.frombuffer(b"".join(spelled), dtype=np.uint8)

    def _table(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Open addressing: key, rank and piece of each slot, key -2 where free; filled at first use, not shipped."""
        if self.slots is None:
            slots = np.full(1 << SLOT_BITS, -1, dtype=np.int32)
            left, place = np.arange(len(self.keys)), _slot(self.keys)
            while len(left):
                place = place % len(slots)
                free = slots[place] < 0
                slots[place[free]] = left[free]  # of several for one slot the last stays
                lost = slots[place] != left
                left, place = left[lost], place[lost] + 1
            free = slots < 0
            self.slots = np.where(free, -2, self.keys[slots]), np.where(free, _NONE, self.ranks[slots]), np.where(free, np.int32(-1), self.merged[slots])
        return self.slots

    def pair(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(rank, piece) of the merge of each pair of symbols; rank _NONE where there is none."""
        key = (a.astype(np.int64) << 20) | b
        key[(a < 0) | (b < 0)] = -1
        keys, ranks, pieces = self._table()
        place = _slot(key)
        at = keys[place]
        lost = at != key
        open_ = np.flatnonzero(lost & (at != -2))
        while len(open_):  # slots taken by another key: look at the next
            place[open_] = (place[open_] + 1) % len(keys)
            at = keys[place[open_]]
            lost[open_] = at != key[open_]
            open_ = open_[(at != -2) & (at != key[open_])]
        return np.where(lost, _NONE, ranks[place]), np.where(lost, np.int32(-1), pieces[place])

    def spell(self, char: str) -> list[int]:
        """Byte pieces of a character outside the vocabulary."""
        return [self.bytes_[b] for b in (MARK if char == LITERAL_MARK else char).encode("utf-8")]

    def decode(self, ids: np.ndarray) -> bytes:
        """Bytes of a sequence of pieces without the leading space."""
        return self.decode_many(ids, np.array([0, len(ids)]))[0].tobytes()

    def decode_many(self, ids: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(bytes, offsets) of many sequences, each without its leading space."""
        size = self.size[ids]
        end = np.cumsum(size)
        total = int(end[-1]) if len(end) else 0
        begin = end - size
        raw = self.blob[np.repeat(self.at[ids] - begin, size) + np.arange(total)]
        bound = np.concatenate([[0], end])[first]
        keep = np.ones(total, dtype=bool)
        filled = np.diff(bound) > 0
        keep[bound[:-1][filled]] = False
        return raw[keep], bound - np.concatenate([[0], np.cumsum(filled)])


def load(path: str = MODEL) -> Vocabulary:
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    n = sp.vocab_size()
    pieces = [sp.id_to_piece(i) for i in range(n)]
    byte = {int(pieces[i][3:5], 16): i for i in range(n) if sp.is_byte(i)}
    normal = [not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)) for i in range(n)]
    return Vocabulary(pieces, [sp.get_score(i) for i in range(n)], byte, normal)


class Encoder:
    def __init__(self, vocab: Vocabulary, dropout: float = DROPOUT, seed: int = SEED):
        self.vocab, self.seed = vocab, seed
        self.bound = min(max(round(dropout * 65536), 0), 65536)

    def keys(self, doc: np.ndarray, place: np.ndarray) -> np.ndarray:
        """The key of each occurrence of a word: seed, document (uint64) and place in it."""
        return mix64(mix64(doc ^ np.uint64(self.seed * 0x9E3779B9), 64) + place.astype(np.uint64), 65)

    def skips(self, keys: np.ndarray, block: int) -> np.ndarray:
        """(n, _LANES) booleans: which of the candidates block * _LANES, ... are skipped."""
        h = mix64(keys + np.uint64(block * 0xD1B54A32D192ED03 % 2**64), 66)
        lanes = (h[:, None] >> (np.arange(_LANES, dtype=np.uint64) * np.uint64(16))) & np.uint64(0xFFFF)
        return lanes < np.uint64(self.bound)

    def mask(self, keys: np.ndarray, out: np.ndarray, upto: np.ndarray, since: np.ndarray | None = None) -> np.ndarray:
        """Set the bits of the candidates below `upto` that are skipped; blocks below `since` are set already."""
        for block in range(-(-int(upto.max(initial=0)) // _LANES)):
            at = np.flatnonzero((upto > block * _LANES) & ((since <= block * _LANES) if since is not None else True))
            if len(at):
                bits = (self.skips(keys[at], block) << np.arange(_LANES)).sum(axis=1).astype(np.uint64)
                out[at] |= bits << np.uint64(block * _LANES)
        return out

    def lockstep(self, codes: np.ndarray, mask: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(pieces of all rows, number of each row's, candidates that came up) of words of one length.

        codes: a row of code points for each word; mask: bit t says that the t-th candidate is skipped.
        """
        v, (m, n) = self.vocab, codes.shape
        chars, inverse = np.unique(codes, return_inverse=True)
        known = np.array([v.id.get(chr(c), -1) for c in chars], dtype=np.int32)
        sym = known[inverse.reshape(-1)]
        alive, pops = np.ones(m * n, dtype=bool), np.zeros(m, dtype=np.int64)
        if n > 1:
            # symbols stay at the place of their first character; left and right are the places of the neighbours
            rank, piece = np.full((m, n), _NONE, dtype=np.int32), np.full((m, n), -1, dtype=np.int32)
            wide = sym.reshape(m, n)
            r, q = v.pair(wide[:, :-1].reshape(-1), wide[:, 1:].reshape(-1))
            rank[:, :-1], piece[:, :-1] = r.reshape(m, n - 1), q.reshape(m, n - 1)
            flat_rank, piece = rank.reshape(-1), piece.reshape(-1)
            at = np.arange(m * n, dtype=np.int32).reshape(m, n)
            right, left = at + 1, at - 1
            right[:, -1] = left[:, 0] = -1
            right, left = right.reshape(-1), left.reshape(-1)
            rows = np.flatnonzero(rank.min(axis=1) < _NONE)
            while len(rows):
                a = rows * n + rank[rows].argmin(axis=1)
                open_ = flat_rank[a] < _NONE
                rows, a = rows[open_], a[open_]
                skip = (mask[rows] >> pops[rows].astype(np.uint64)) & np.uint64(1) > 0
                pops[rows] += 1
                flat_rank[a[skip]] = _NONE
                a = a[~skip]
                b = right[a]
                c, p = right[b], left[a]
                sym[a], alive[b], flat_rank[a], flat_rank[b], right[a] = piece[a], False, _NONE, _NONE, c
                after, before = c >= 0, p >= 0
                left[c[after]] = a[after]
                one, two = np.concatenate([p[before], a[after]]), np.concatenate([a[before], c[after]])
                flat_rank[one], piece[one] = v.pair(sym[one], sym[two])
        size = alive.reshape(m, n).sum(axis=1)
        flat = sym[alive]
        strange = np.flatnonzero(((sym < 0) & alive).reshape(m, n).any(axis=1))
        if len(strange):  # characters outside the vocabulary
            first = np.concatenate([[0], np.cumsum(size)])
            parts, done = [], 0
            for i in strange:
                ids: list[int] = []
                for s, c in zip(flat[first[i] : first[i + 1]].tolist(), codes[i][alive[i * n : (i + 1) * n]].tolist()):
                    ids += [s] if s >= 0 else v.spell(chr(c))
                parts += [flat[done : first[i]], np.array(ids, dtype=np.int32)]
                done = first[i + 1]
                size[i] = len(ids)
            flat = np.concatenate([*parts, flat[done:]])
        return flat, size, pops

    def heap(self, text: str, key: np.uint64) -> np.ndarray:
        """One occurrence of a word by a heap: n log n for any length."""
        v, n = self.vocab, len(text)
        keys = np.array([key], dtype=np.uint64)
        sym = [v.id.get(c, -1) for c in text]
        prev, nxt = list(range(-1, n - 1)), list(range(1, n + 1))
        end = list(range(1, n + 1))
        alive = [True] * n
        agenda: list[tuple[int, int, int, int, int]] = []
        table: dict[int, tuple[int, int]] = {}

        def push(a: int) -> None:
            b = nxt[a]
            if b >= n or sym[a] < 0 or sym[b] < 0:
                return
            k = (sym[a] << 20) | sym[b]
            got = table.get(k)
            if got is None:
                r, m = v.pair(np.array([sym[a]]), np.array([sym[b]]))
                got = table[k] = (int(r[0]), int(m[0]))
            if got[0] != _NONE:
                heapq.heappush(agenda, (got[0], a, b, end[b], got[1]))

        for a in range(n - 1):
            push(a)
        t, skipped = 0, []
        while agenda:
            _, a, b, stop, merged = heapq.heappop(agenda)
            if not (alive[a] and b < n and alive[b]) or nxt[a] != b or end[b] != stop:
                continue
            if t >= len(skipped):
                blocks = range(len(skipped) // _LANES, len(skipped) // _LANES + 64)
                skipped += np.concatenate([self.skips(keys, block)[0] for block in blocks]).tolist()
            t += 1
            if skipped[t - 1]:
                continue
            sym[a], end[a], alive[b] = merged, stop, False
            nxt[a] = nxt[b]
            if nxt[b] < n:
                prev[nxt[b]] = a
            if prev[a] >= 0:
                push(prev[a])
            push(a)
        flat: list[int] = []
        a = 0
        while a < n:
            flat += [sym[a]] if sym[a] >= 0 else v.spell(text[a])
            a = nxt[a]
        return np.array(flat, dtype=np.int32)


class _Table:
    """Sorted 64-bit keys and the numbers they stand for."""

    def __init__(self):
        self.keys, self.values = np.zeros(0, np.uint64), np.zeros(0, np.int32)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The number of each key, -1 where there is none."""
        if not len(self.keys):
            return np.full(len(keys), -1, dtype=np.int32)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, self.values[at], np.int32(-1))

    def add(self, keys: np.ndarray, values: np.ndarray) -> None:
        """Add sorted new keys."""
        at = np.searchsorted(self.keys, keys)
        self.keys, self.values = np.insert(self.keys, at, keys), np.insert(self.values, at, values.astype(np.int32))


class _Pool:
    """A growing array that is written at its end."""

    def __init__(self, kind):
        self.data, self.n = np.zeros(1 << 12, dtype=kind), 0

    def add(self, values: np.ndarray) -> None:
        if self.n + len(values) > len(self.data):
            grown = np.zeros(max(self.n + len(values), len(self.data) * 3 // 2), dtype=self.data.dtype)
            grown[: self.n] = self.data[: self.n]
            self.data = grown
        self.data[self.n : self.n + len(values)] = values
        self.n += len(values)


class CorpusEncoder:
    """Encodes texts, remembering a bounded number of nodes of the words' trees."""

    def __init__(self, encoder: Encoder, nodes: int = NODES):
        self.encoder, self.most = encoder, nodes
        self._forget()

    def _forget(self) -> None:
        self.roots, self.children = _Table(), _Table()
        # of a word: code points; of a node: its word, what it skips, candidates that come up, and its pieces
        self.codes, self.code_at, self.code_n = _Pool(np.uint32), _Pool(np.int64), _Pool(np.int32)
        self.word, self.skipped, self.pops = _Pool(np.int32), _Pool(np.uint64), _Pool(np.uint8)
        self.pieces, self.piece_at, self.piece_n = _Pool(np.int32), _Pool(np.int64), _Pool(np.int32)

    def _grow(self, word: np.ndarray, mask: np.ndarray) -> np.ndarray:
        """New nodes for words and masks; their numbers."""
        base, total = self.word.n, len(word)
        n, pops = self.code_n.data[word], np.zeros(total, dtype=np.uint8)
        at, count = np.zeros(total, dtype=np.int64), np.zeros(total, dtype=np.int32)
        for k in np.unique(n).tolist():
            own = np.flatnonzero(n == k)
            step = max(1, 200_000 // k)
            for lo in range(0, len(own), step):
                i = own[lo : lo + step]
                codes = self.codes.data[self.code_at.data[word[i]][:, None] + np.arange(k)]
                flat, size, came = self.encoder.lockstep(codes, mask[i])
                at[i] = self.pieces.n + np.cumsum(size) - size
                count[i], pops[i] = size, came
                self.pieces.add(flat)
        for pool, values in ((self.word, word), (self.skipped, mask), (self.pops, pops), (self.piece_at, at), (self.piece_n, count)):
            pool.add(values)
        return np.arange(base, base + total, dtype=np.int32)

    def _root(self, raw: np.ndarray, start: np.ndarray, end: np.ndarray, key: np.ndarray) -> None:
        """Remember the new words raw[start:end], whose hashes are `key`, sorted, as roots."""
        size = end - start
        first = np.cumsum(size) - size
        text = raw[np.repeat(start - first, size) + np.arange(int(size.sum()))]
        letters = (text & 0xC0) != 0x80
        chars = np.add.reduceat(letters, first).astype(np.int32)
        marked = text.tobytes().decode().replace(MARK, LITERAL_MARK).replace(" ", MARK)
        base = self.code_at.n
        self.code_at.add(self.codes.n + np.cumsum(chars) - chars)
        self.code_n.add(chars)
        self.codes.add(np.frombuffer(marked.encode("utf-32-le", "surrogatepass"), dtype=np.uint32))
        words = np.arange(base, base + len(start), dtype=np.int32)
        self.roots.add(key, self._grow(words, np.zeros(len(start), dtype=np.uint64)))

    def encode(self, raw: np.ndarray, offsets: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(pieces of all texts, bounds of each text's) of texts in a byte buffer; doc: their ids as uint64."""
        flat, bound = self._encode(raw, offsets, doc)
        # words are told apart by 64-bit hashes: a text that doesn't decode to itself is encoded word by word
        back, at = self.encoder.vocab.decode_many(flat, bound)
        if np.array_equal(at, offsets) and np.array_equal(back, raw):
            return flat, bound
        parts = []
        for i in range(len(doc)):
            own = flat[bound[i] : bound[i + 1]]
            if not np.array_equal(back[at[i] : at[i + 1]], raw[offsets[i] : offsets[i + 1]]):
                self._forget()
                own = self._encode(raw[offsets[i] : offsets[i + 1]], offsets[i : i + 2] - offsets[i], doc[i : i + 1], alone=True)[0]
            parts.append(own)
        return np.concatenate(parts), np.concatenate([[0], np.cumsum([len(p) for p in parts])])

    def _encode(self, raw: np.ndarray, offsets: np.ndarray, doc: np.ndarray, alone: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """alone: by heap only, without a table of words."""
        if self.word.n > self.most:
            self._forget()
        filled = np.diff(offsets) > 0
        if not filled.any():
            return np.zeros(0, np.int32), np.zeros(len(offsets), np.int64)
        raw = np.insert(raw, offsets[:-1][filled], 32)  # the leading space
        offsets = offsets + np.concatenate([[0], np.cumsum(filled)])
        space, apart = raw == 32, self.encoder.vocab.apart[raw]
        begins = apart.copy()
        begins[1:] |= apart[:-1]
        begins[1:] |= space[1:] & ~space[:-1]
        begins[offsets[:-1][filled]] = True
        start = np.flatnonzero(begins)
        end = np.append(start[1:], len(raw))
        first = np.searchsorted(start, offsets)
        place = np.arange(len(start)) - np.repeat(first[:-1], np.diff(first))
        keys = self.encoder.keys(np.repeat(doc, np.diff(first)), place)
        long_ = np.add.reduceat((raw & 0xC0) != 0x80, start) > LOCKSTEP
        node = np.full(len(start), -1, dtype=np.int32)
        if alone:
            long_[:] = True
        else:
            short = np.flatnonzero(~long_)
            node[short] = self._nodes(raw, start[short], end[short], keys[short])
        at, size = np.where(long_, 0, self.piece_at.data[node]), np.where(long_, 0, self.piece_n.data[node])
        pool = self.pieces.data[: self.pieces.n]
        if long_.any():
            own = [self.encoder.heap(raw[start[i] : end[i]].tobytes().decode().replace(MARK, LITERAL_MARK).replace(" ", MARK), keys[i]) for i in np.flatnonzero(long_)]
            size[long_] = [len(x) for x in own]
            at[long_] = len(pool) + np.cumsum(size[long_]) - size[long_]
            pool = np.concatenate([pool, *own])
        stop = np.cumsum(size, dtype=np.int64)
        total = int(stop[-1])
        flat = pool[np.repeat(at - stop + size, size) + np.arange(total)]
        return flat, np.concatenate([[0], stop])[first]

    def _nodes(self, raw: np.ndarray, start: np.ndarray, end: np.ndarray, keys: np.ndarray) -> np.ndarray:
        """The node at which each occurrence of a short word ends."""
        word, at, inverse = np.unique(spans_hash(raw, start, end), return_index=True, return_inverse=True)
        root = self.roots.find(word)
        new = root < 0
        if new.any():
            self._root(raw, start[at[new]], end[at[new]], word[new])
            root = self.roots.find(word)
        node = root[inverse]
        upto = self.pops.data[node].astype(np.int64)
        mask = self.encoder.mask(keys, np.zeros(len(node), dtype=np.uint64), upto)
        one = np.uint64(1)
        walk = np.flatnonzero(mask & ((one << upto.astype(np.uint64)) - one))
        if not len(walk):
            return node
        # a path with skips may meet more candidates than the one without
        most = 3 * (self.code_n.data[self.word.data[node[walk]]].astype(np.int64) - 1)
        bits = self.encoder.mask(keys[walk], mask[walk], most, -(-upto[walk] // _LANES) * _LANES)
        since = np.zeros(len(walk), dtype=np.uint64)
        while len(walk):
            open_ = bits & ((one << self.pops.data[node[walk]].astype(np.uint64)) - one) & ~((one << since) - one)
            go = np.flatnonzero(open_)
            walk, bits, open_ = walk[go], bits[go], open_[go]
            if not len(walk):
                break
            j = np.bitwise_count((open_ & (~open_ + one)) - one).astype(np.uint64)
            edge, index, inverse = np.unique((node[walk].astype(np.uint64) << np.uint64(6)) | j, return_index=True, return_inverse=True)
            child = self.children.find(edge)
            new = np.flatnonzero(child < 0)
            if len(new):
                parent = node[walk[index[new]]]
                grown = self._grow(self.word.data[parent], self.skipped.data[parent] | (one << j[index[new]]))
                self.children.add(edge[new], grown)
                child[new] = grown
            node[walk] = child[inverse]
            since = j + one
        return node


def encode(docs: DataFrame, vocab: Vocabulary, dropout: float = DROPOUT, seed: int = SEED, full: bool = True) -> DataFrame:
    """Pieces of every row: (doc_id, ids) if full, else the digest (doc_id, n_pieces, ids_sha256, n_bytes, lossless).

    The digest decodes what was encoded and compares it with the text.
    """

    def run(batches):
        coder = CorpusEncoder(Encoder(vocab, dropout, seed))
        for batch in batches:
            raw, offsets = buffers(column(batch, "text"))
            number = column(batch, "doc_id").fill_null(0).to_numpy().view(np.uint64)
            for a, b in slices(offsets):
                ids = column(batch, "doc_id").slice(a, b - a)
                part, off = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
                flat, first = coder.encode(part, off, number[a:b])
                if full:
                    yield pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(flat))], names=["doc_id", "ids"])
                    continue
                out, bound = vocab.decode_many(flat, first)
                if np.array_equal(bound, off) and np.array_equal(out, part):
                    same = np.ones(b - a, dtype=bool)
                else:
                    same = np.array([np.array_equal(out[bound[i] : bound[i + 1]], part[off[i] : off[i + 1]]) for i in range(b - a)])
                sha = [hashlib.sha256(flat[first[i] : first[i + 1]]).hexdigest() for i in range(b - a)]
                yield pa.RecordBatch.from_arrays(
                    [ids, pa.array(np.diff(first)), pa.array(sha), pa.array(np.diff(off)), pa.array(same)],
                    names=["doc_id", "n_pieces", "ids_sha256", "n_bytes", "lossless"],
                )

    small_batches(docs.sparkSession)
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, ids array<int>" if full else "doc_id long, n_pieces long, ids_sha256 string, n_bytes long, lossless boolean"
    return src.mapInArrow(released(lambda it: run(x for x in it if x.num_rows)), schema)


def decode(encoded: DataFrame, vocab: Vocabulary) -> DataFrame:
    """(doc_id, text) of rows (doc_id, ids); null ids decode to null."""

    def run(batch: pa.RecordBatch):
        rows = column(batch, "ids").to_pylist()
        text = [None if r is None else vocab.decode(np.array(r, dtype=np.int64)).decode() for r in rows]
        yield pa.RecordBatch.from_arrays([column(batch, "doc_id"), pa.array(text, pa.string())], names=["doc_id", "text"])

    return map_batches(encoded.select("doc_id", "ids"), run, "doc_id long, text string")


def op5(spark, sf_dir: str) -> DataFrame:
    return encode(spark.read.parquet(f"{sf_dir}/documents.parquet"), load(), full=False)
