"""Operators against brute force, exact round trips, SQL and held-out accuracy."""

import math
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import sentencepiece
from hypothesis import given, settings
from hypothesis import strategies as st

import corpus_pipeline
from oracle import assert_same, connect
from pyspark.sql import functions as F
from skewjoin.llm import embdup, neardup, queries, sptok, substr, toxicity, wordhash
from skewjoin.llm.common import components


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_matches_sql(spark, small, name):
    assert_same(queries.QUERIES[name](spark, small), queries.ORACLES[name], small)


# ---- words and hashes ----

TEXT = st.text(alphabet=st.sampled_from(list("ab \n\té▁\x0b\x0c\r\x1f\x85")), max_size=40)


@settings(max_examples=80, deadline=None)
@given(st.lists(TEXT, max_size=8))
def test_words_are_those_of_a_plain_split(texts):
    raw, off = wordhash.buffers(pa.array(texts, pa.string()))
    w = wordhash.Words(raw, off)
    got = [bytes(raw[a:b]) for a, b in zip(w.start, w.end)]
    assert got == [x for t in texts for x in t.encode().split()]
    assert w.counts().tolist() == [len(t.encode().split()) for t in texts]
    h = w.hashes()
    assert len(set(zip(got, h.tolist()))) == len(set(got)) == len(set(h.tolist()))
    win, inside = wordhash.windows(h, w.first, 3)
    seen = {}
    for i in np.flatnonzero(inside):
        assert seen.setdefault(tuple(got[i : i + 3]), win[i]) == win[i]
    assert inside.sum() == sum(max(0, len(t.encode().split()) - 2) for t in texts)


# ---- near duplicates and substrings against brute force ----


def corpus(seed, n=60):
    rng = random.Random(seed)
    word = lambda: rng.choice("abcdefghij") * rng.randrange(1, 3)
    bases = [[word() + str(rng.randrange(9)) for _ in range(rng.randrange(0, 60))] for _ in range(8)]
    out = []
    for i in range(n):
        w = list(rng.choice(bases))
        for _ in range(rng.choice([0, 0, 1, 2, 5])):
            if w:
                w[rng.randrange(len(w))] = word()
        out.append((i * 3 + rng.randrange(3), " ".join(w)))
    return out


def brute_components(rows, k, percent):
    sets = {}
    for i, t in rows:
        w = t.lower().split()
        sets[i] = {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for x in ids:
        for y in ids:
            if x < y and sets[x] and sets[y]:
                both = len(sets[x] & sets[y])
                if 100 * both >= percent * (len(sets[x]) + len(sets[y]) - both):
                    a, b = sorted((find(x), find(y)))
                    root[b] = a
    return {i: (len(sets[i]), find(i)) for i in ids}


@pytest.mark.parametrize("seed, k, percent", [(1, 3, 85), (2, 5, 80), (3, 1, 90)])
def test_near_duplicates_against_brute_force(spark, seed, k, percent):
    rows = corpus(seed)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in neardup.near_duplicates(df, k, percent).collect()}
    assert got == brute_components(rows, k, percent)


def test_large_groups_are_dealt_into_blocks(spark, monkeypatch):
    """Small blocks: the same components."""
    from skewjoin.llm import grouping

    monkeypatch.setattr(grouping, "BLOCK", 4)
    monkeypatch.setattr(grouping, "SMALL", 3)
    monkeypatch.setattr(neardup, "CLUSTER_BLOCK", 5)
    rows = corpus(7, 90)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in neardup.near_duplicates(df, 3, 85).collect()}
    assert got == brute_components(rows, 3, 85)


@pytest.mark.parametrize("percent", [80, 85])
def test_links_at_the_threshold_are_hardly_ever_lost(percent):
    """The probability that the estimate of a pair at the threshold falls under the cutoff."""
    n, p = neardup.PERMUTATIONS, percent / 100 + (1 - percent / 100) / 2**neardup.BITS
    chance = 1 / 2**neardup.BITS
    lost = [m for m in range(n + 1) if (m / n - chance) / (1 - chance) < percent / 100 - neardup.MARGIN]
    assert sum(math.comb(n, m) * p**m * (1 - p) ** (n - m) for m in lost) < 1e-4


def test_similarity_estimate_is_corrected():
    rng = np.random.default_rng(0)
    a = rng.integers(0, 1 << 32, (200, neardup.PERMUTATIONS), dtype=np.uint64).astype(np.uint32)
    b = a.copy()
    differ = rng.random(b.shape) < 0.3
    b[differ] = rng.integers(0, 1 << 32, int(differ.sum()), dtype=np.uint64).astype(np.uint32)
    s = neardup.similarity(neardup.packed(a), neardup.packed(b))
    assert abs(s.mean() - 0.7) < 0.02
    assert (neardup.similarity(neardup.packed(a), neardup.packed(a)) == 1).all()


def brute_removal(rows, window):
    first = {}
    for i, t in sorted(rows):
        w = t.split()
        for j in range(len(w) - window + 1):
            first.setdefault(tuple(w[j : j + window]), i)
    out = {}
    for i, t in rows:
        w = t.split()
        gone = set()
        for j in range(len(w) - window + 1):
            if first[tuple(w[j : j + window])] < i:
                gone.update(range(j, j + window))
        out[i] = [x for j, x in enumerate(w) if j not in gone]
    return out


@pytest.mark.parametrize("seed, window", [(1, 13), (4, 5), (5, 3)])
def test_substrings_against_brute_force(spark, seed, window):
    rows = corpus(seed)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    want = brute_removal(rows, window)
    got = {r["doc_id"]: r["text"].split() for r in substr.remove_repeats(df, window).collect()}
    assert got == want
    digest = {r["doc_id"]: (r["n_words"], r["n_removed"]) for r in substr.removal_digest(df, window).collect()}
    assert digest == {i: (len(t.split()), len(t.split()) - len(want[i])) for i, t in rows}


def test_common_minimizers_change_the_placement_only():
    texts = ["a b c d e f g h i j k l m n o p", "x a b c d e f g h i j k l m n", "a b c d e f g h i j k l m"]
    raw, off = wordhash.buffers(pa.array(texts))
    ids = np.array([5, 7, 9])
    plain = substr.Slice(raw, off, 13, 8, np.zeros(0, np.uint64))
    hot = np.unique(wordhash.mix64(plain.mini, 21))
    for h in (np.zeros(0, np.uint64), hot):
        found = []
        buckets = {}
        for b, i, r, z in substr.pack_slice(ids, raw, off, 13, 8, h):
            buckets.setdefault(b, []).append((i, r, z))
        for rows in buckets.values():
            d, s, n = substr.judge(rows)
            found += list(zip(d.tolist(), s.tolist(), n.tolist()))
        flagged = {(d, s + i) for d, s, n in found for i in range(n)}
        assert flagged == {(7, 1), (7, 2), (9, 0)}


# ---- embeddings ----


def test_embeddings_against_brute_force(spark):
    rng = np.random.default_rng(3)
    centre = rng.normal(size=(40, 64))
    x = np.concatenate([centre[rng.integers(0, 40, 500)] + rng.normal(size=(500, 64)) * rng.choice([0.1, 0.2, 0.3], (500, 1)), rng.normal(size=(300, 64))]).astype(np.float32)
    x[10] = x[11]
    df = spark.createDataFrame([(int(i), [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<float>").repartition(4)
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embdup.near_vectors(df).collect()}
    u = x.astype(np.float64)
    u /= np.linalg.norm(u, axis=1)[:, None]
    near = u @ u.T >= 0.9
    np.fill_diagonal(near, False)
    degree = near.sum(1)
    found = sum(got[i][0] for i in range(len(x)))
    assert found >= 0.98 * degree.sum() and all(got[i][0] <= degree[i] for i in range(len(x)))
    root = np.arange(len(x))
    for _ in range(50):
        root = np.minimum(root, np.where(near, root[None], len(x)).min(1))
    assert np.mean([got[i][1] == root[i] for i in range(len(x))]) >= 0.98


def test_embeddings_in_a_dense_region_keep_their_links(spark):
    """True partners that have many closer non-links by Hamming distance are found all the same."""
    rng = np.random.default_rng(12)
    dim, n, dense = 64, 2700, 700
    centre = rng.normal(size=dim)
    centre /= np.linalg.norm(centre)
    noise = rng.normal(size=(dense, dim))
    noise /= np.linalg.norm(noise, axis=1)[:, None]
    x = np.concatenate([centre + noise * 0.42, rng.normal(size=(n - dense, dim))])  # most cosines of the region lie a little under 0.9
    u = x / np.linalg.norm(x, axis=1)[:, None]
    for i in range(0, dense, 14):  # a partner at a cosine of about 0.905
        side = rng.normal(size=dim)
        side -= (side @ u[i]) * u[i]
        u[i + 1] = 0.905 * u[i] + np.sqrt(1 - 0.905**2) * side / np.linalg.norm(side)
    df = spark.createDataFrame([(int(i), [float(v) for v in r]) for i, r in enumerate(u)], "vec_id long, embedding array<double>").repartition(4)
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embdup.near_vectors(df).collect()}
    near = u @ u.T >= 0.9
    np.fill_diagonal(near, False)
    assert sum(got[i][0] for i in range(n)) >= 0.995 * near.sum()
    root = np.arange(n)
    for _ in range(100):
        root = np.minimum(root, np.where(near, root[None], n).min(1))
    assert np.mean([got[i][1] == root[i] for i in range(n)]) >= 0.99


def test_rotation_is_orthogonal_and_balanced():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(500, 32))
    x /= np.linalg.norm(x, axis=1)[:, None]
    rot = embdup.learn_rotation(x)
    for part in (rot.project[:, :32], rot.project[:, 32:]):  # two rotations, of 32 bits each
        assert np.allclose(part.T @ part, np.eye(32), atol=1e-8)
    bits = ((x - rot.mean) @ rot.project > 0).mean(0)
    assert (abs(bits - 0.5) < 0.2).all()


# ---- components ----


@pytest.mark.parametrize("seed", range(3))
def test_components(spark, seed, monkeypatch):
    from skewjoin.llm import common

    if seed:  # the centre of the star is sent to its edges
        monkeypatch.setattr(common, "HUB_ROWS", 5)
        monkeypatch.setattr(common, "HUBS", 20)
    rng = random.Random(seed)
    edges = [(rng.randrange(60), rng.randrange(60)) for _ in range(40)] + [(i, i + 1) for i in range(100, 140)] + [(200, i) for i in range(201, 260)]
    root = {}

    def find(v):
        while root.setdefault(v, v) != v:
            v = root[v]
        return v

    for a, b in edges:
        x, y = sorted((find(a), find(b)))
        root[y] = x
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {v: find(v) for a, b in edges if a != b for v in (a, b)}


# ---- tokens ----


@pytest.fixture(scope="module")
def vocab():
    return sptok.load()


@pytest.fixture(scope="module")
def texts(small):
    return [r[0] for r in connect(small).execute("SELECT text FROM documents ORDER BY doc_id LIMIT 80").fetchall()]


def encoded(vocab, texts, p=0.1, seed=11, ids=None, **options):
    coder = sptok.CorpusEncoder(sptok.Encoder(vocab, p, seed), **options)
    raw, off = wordhash.buffers(pa.array(texts, pa.string()))
    out = []
    for a, b in wordhash_slices(off):
        flat, at = coder.encode(raw[off[a] : off[b]], off[a : b + 1] - off[a], np.array(ids or range(len(texts)), dtype=np.uint64)[a:b])
        out += [flat[at[i] : at[i + 1]].tolist() for i in range(b - a)]
    return out


def wordhash_slices(off):
    from skewjoin.llm.common import slices

    return slices(off, 50_000)


def test_without_dropout_the_pieces_are_the_library_s(vocab, texts):
    sp = sentencepiece.SentencePieceProcessor(model_file=sptok.MODEL)
    assert encoded(vocab, texts, 0.0) == [sp.encode(t) for t in texts]


def test_dropout_varies_repeats_and_decodes(vocab, texts):
    a, b, c = encoded(vocab, texts, 0.2, 1), encoded(vocab, texts, 0.2, 1, nodes=500), encoded(vocab, texts, 0.2, 2)
    assert a == b and sum(x != y for x, y in zip(a, c)) > len(texts) // 2
    for got in (a, c, encoded(vocab, texts, 1.0)):
        assert [vocab.decode(np.array(g, np.int32)).decode() for g in got] == texts
    n = [sum(map(len, encoded(vocab, texts, p))) for p in (0.5, 0.2, 0.0)]
    assert n[0] > n[1] > n[2]


def test_every_occurrence_draws_its_own_segmentation(vocab):
    """Of one long word, more segmentations than a few, in one text and over documents."""
    word = " international"
    one = encoded(vocab, [word * 400], 0.3)[0]
    parts, own = set(), []
    for piece in one:
        own.append(piece)
        if vocab.decode(np.array([1, *own][1:], np.int32)).decode().endswith("l"):
            parts.add(tuple(own))
            own = []
    assert len(parts) > 20
    assert len({tuple(x) for x in encoded(vocab, ["international"] * 200, 0.3)}) > 10
    twice = encoded(vocab, ["international affairs", "international affairs"], 0.3, ids=[5, 5])
    assert twice[0] == twice[1]


def agenda(vocab, merges, text, skips):
    """Pieces of one word by a plain loop: the best adjacent pair that wasn't skipped, leftmost among equals."""
    parts = [(i, i + 1, vocab.id.get(c, -1)) for i, c in enumerate(text)]
    gone, t = set(), 0
    while True:
        best = None
        for i, ((a, b, x), (_, c, y)) in enumerate(zip(parts, parts[1:])):
            found = merges.get((x << 20) | y) if x >= 0 and y >= 0 else None
            if found and (a, b, c) not in gone and (best is None or found[0] < best[0]):
                best = (found[0], i, found[1])
        if best is None:
            break
        i = best[1]
        a, b, c = parts[i][0], parts[i][1], parts[i + 1][1]
        if skips(t):
            gone.add((a, b, c))
        else:
            parts[i : i + 2] = [(a, c, best[2])]
        t += 1
    out = []
    for a, _, x in parts:
        out += [x] if x >= 0 else vocab.spell(text[a])
    return out


@pytest.mark.parametrize("p", [0.1, 0.4])
def test_dropout_against_a_plain_agenda(vocab, texts, p):
    e = sptok.Encoder(vocab, p, 3)
    merges = {int(k): (int(r), int(m)) for k, r, m in zip(vocab.keys, vocab.ranks, vocab.merged)}
    some = [t[:600] for t in texts[:12]] + ["x" * 70 + " ab\tc ▁ \n\x0b 日本 " + "na" * 15]
    for i, (t, got) in enumerate(zip(some, encoded(vocab, some, p, 3))):
        marked = "▁" + t.replace("▁", sptok.LITERAL_MARK).replace(" ", "▁")
        words, own = [], ""
        for before, c in zip(" " + marked, marked):  # a word starts at a run of marks, and at white space
            if own and (c in "\t\n\x0b\x0c\r" or before in "\t\n\x0b\x0c\r" or (c == "▁" and before != "▁")):
                words.append(own)
                own = ""
            own += c
        want = []
        for place, w in enumerate([*words, own]):
            key = e.keys(np.array([i], np.uint64), np.array([place]))
            want += agenda(vocab, merges, w, lambda t, key=key: bool(e.skips(key, t // 4)[0][t % 4]))
        assert got == want


@settings(max_examples=60, deadline=None)
@given(st.text(max_size=60))
def test_any_text_round_trips(text):
    vocab = _vocab()
    got = encoded(vocab, [text], 0.3)[0]
    assert vocab.decode(np.array(got, np.int32)).decode() == text


_KEPT: list = []


def _vocab():
    if not _KEPT:
        _KEPT.append(sptok.load())
    return _KEPT[0]


def test_trees_equal_the_heap(vocab, texts):
    e = sptok.Encoder(vocab, 0.3)
    for i, t in enumerate(texts[:20]):
        raw, off = wordhash.buffers(pa.array([t]))
        doc = np.array([i], dtype=np.uint64)
        assert encoded(vocab, [t], 0.3, ids=[i])[0] == sptok.CorpusEncoder(e)._encode(raw, off, doc, alone=True)[0].tolist()


# ---- classifiers on held-out rows ----


def held_out(spark, folder, name, truth, column):
    rows = queries.QUERIES[name](spark, folder).where("held_out").collect()
    want = dict(connect(folder).execute(truth).fetchall())
    return [(r, want[r["doc_id"]]) for r in rows if r["doc_id"] in want and column is not None]


def test_language_on_held_out_rows(spark, oracle_dir):
    rows = held_out(spark, oracle_dir, "op1_language_id", "SELECT doc_id, lang FROM documents WHERE lang IS NOT NULL AND length(text) > 20", "lang")
    assert sum(r["lang_pred"] == y for r, y in rows) / len(rows) > 0.97


def test_quality_on_held_out_rows(spark, oracle_dir):
    rows = held_out(spark, oracle_dir, "op4_quality_classifier", "SELECT doc_id, quality FROM labels", "quality")
    assert sum(r["predicted"] == y for r, y in rows) / len(rows) > 0.9


def test_toxicity_on_held_out_rows(spark, oracle_dir):
    rows = held_out(spark, oracle_dir, "op7_toxicity", "SELECT doc_id, toxic FROM labels", "toxic")
    clean = [r["predicted"] for r, y in rows if y == 0]
    assert sum(clean) / len(clean) < 0.1
    by = sorted((r["score"], y) for r, y in rows)
    bad = sum(y for _, y in by)
    auc = (sum(i + 1 for i, (_, y) in enumerate(by) if y) - bad * (bad + 1) / 2) / (bad * (len(by) - bad))
    assert auc > 0.75


def test_toxicity_learns_from_the_ends_of_long_texts(spark):
    """Toxic passages that stand after thousands of calm characters, in every labelled text, are counted."""
    rng = random.Random(4)
    calm = lambda n: " ".join(rng.choice(CALM) + rng.choice("aeiou") for _ in range(n))
    rows = [(i, calm(1200) + (f" vile brute go away {calm(1)}" * 6 if i % 3 == 0 else ""), int(i % 3 == 0)) for i in range(240)]
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows], "doc_id long, text string").repartition(3)
    labels = spark.createDataFrame([(i, y) for i, _, y in rows], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels, F.lit(True))
    probe = spark.createDataFrame([(1, calm(60)), (2, calm(30) + " vile brute go away" * 4)], "doc_id long, text string")
    got = {r["doc_id"]: r["score"] for r in toxicity.score(probe, model).collect()}
    assert got[2] > 0.5 > got[1]
    words = {n: toxicity._tokens(*wordhash.buffers(pa.array([n])))[0] for n in ("vile", "brute")}
    assert all(model.kn.llr(w, np.zeros(1, np.uint64))[0] > model.kn.base + 0.3 for w in words.values())


def naive_ratio(rows, errors):
    """log p1(w | v) - log p0(w | v) by dictionaries, from (text, class, weight): the definition in the module's text."""
    n, c, b, total = Counter(), Counter(), Counter(), [0.0, 0.0]
    for text, y, weight in rows:
        words = re.findall("[a-z]+", text.lower())
        for v, w in set(zip(["<s>", *words], words)):
            n[w, y] += weight
            c[v, y] += weight
            b[v, w, y] += weight
            total[y] += weight
    share = [t / sum(total) for t in total]

    def left(count, pooled, own, other):
        return max(count - max(0.5 + pooled + errors * math.sqrt(pooled * (1 - own)), toxicity.TIMES * other), 0.0)

    vocab = {w for w, _ in n}
    shared = {w: (n[w, 0] + n[w, 1]) / sum(total) for w in vocab}
    rest = {(w, y): left(n[w, y], total[y] * shared[w], share[y], n[w, 1 - y] * total[y] / total[1 - y]) for w in vocab for y in (0, 1)}
    lam = [1 - sum(rest[w, y] for w in vocab) / total[y] for y in (0, 1)]
    p = lambda w, y: rest[w, y] / total[y] + lam[y] * shared[w]
    known = {(v, w) for v, w, _ in b if v in vocab}
    more = {}
    for v, w in known:
        own = [max(c[v, y], 1e-9) for y in (0, 1)]
        for y in (0, 1):
            pooled = (b[v, w, 0] + b[v, w, 1]) / sum(own)
            more[v, w, y] = left(b[v, w, y], own[y] * max(pooled, p(w, y)), own[y] / sum(own), max(b[v, w, 1 - y] * own[y] / own[1 - y], own[y] * p(w, y)))

    def prob(v, w, y):
        used = min(sum(more[x, z, y] for x, z in known if x == v) / max(c[v, y], 1e-9), 0.999)
        return (more.get((v, w, y), 0) / max(c[v, y], 1e-9) if v in vocab else 0) + (1 - used) * p(w, y)

    return lambda v, w: math.log(prob(v, w, 1)) - math.log(prob(v, w, 0)) if w in vocab else math.log(lam[1]) - math.log(lam[0])


@pytest.mark.parametrize("seed", [1, 2])
def test_toxicity_ratios_are_those_of_the_definition(spark, seed, monkeypatch):
    """Counts by Spark over labelled texts with near copies, against dictionaries; every word of every text."""
    monkeypatch.setattr(toxicity, "LEAST", 0.0)
    rng = random.Random(seed)
    word = lambda: rng.choice(CALM[:6]) + rng.choice("ab")
    texts = []
    for i in range(160):
        body = [word() for _ in range(rng.randrange(8, 40))]
        y = int(i % 4 == 0)
        if y:
            body[rng.randrange(len(body)) :] = ["vile", "brute", "go"] + body[-3:]
        texts += [(" ".join(body), y)] * rng.choice([1, 1, 1, 4])
    docs = spark.createDataFrame(list(enumerate(t for t, _ in texts)), "doc_id long, text string").repartition(3)
    labels = spark.createDataFrame([(i, y) for i, (_, y) in enumerate(texts)], "doc_id long, toxic int")
    rows = toxicity.learned(docs, labels, F.lit(True)).select("doc_id", "text")
    groups = toxicity.copy_groups(toxicity.learned(docs, labels, F.lit(True)))
    weighted = [(r["text"], r["y"], r["weight"] / toxicity.UNIT) for r in rows.join(groups, "doc_id").collect()]
    assert sum(w for _, _, w in weighted) < 0.8 * len(texts)
    model = toxicity.fit(docs, labels, F.lit(True)).kn
    want = naive_ratio(weighted, model.errors)
    told = 0
    for text, _ in texts[::7]:
        words = re.findall("[a-z]+", text)
        w, v, _ = toxicity._tokens(*wordhash.buffers(pa.array([text])))
        got = model.llr(w, v)
        exact = [want(x, y) for x, y in zip(["<s>", *words], words)]
        assert np.allclose(got, exact, atol=2e-4)
        told += sum(abs(x - model.base) > 0.5 for x in got)
    assert told


CALM = ["river", "hill", "tree", "cloud", "stone", "field", "bridge", "garden", "lamp", "winter", "bread", "paper"]


# ---- convolution and curriculum against plain loops ----


def test_convolution_against_a_loop():
    """Pooled responses of every block, by positions, filters and bytes one at a time."""
    from skewjoin.llm import bytecnn

    net = bytecnn.ByteCNN(3, 2, 16, seed=5)
    texts = ["a short one", "", "something longer than a single block of bytes, é and all", "x" * 16]
    raw, off = wordhash.buffers(pa.array(texts))
    buf, first = bytecnn.layout(raw, off, net.block)
    got = net.pool(buf, step=32)
    emb, w = net.p["E"].astype(float), net.p["W"].astype(float)
    padded = bytes(buf) + bytes(bytecnn.WIDTH)
    for block in range(len(buf) // net.block):
        for f in range(net.filters):
            best = -math.inf
            for at in range(block * net.block, (block + 1) * net.block):
                x = sum(float(emb[padded[at + k], e]) * float(w[k * bytecnn.EMB + e, f]) for k in range(bytecnn.WIDTH) for e in range(bytecnn.EMB))
                best = max(best, x)
            assert abs(best - got[block, f]) < 1e-4
    assert first.tolist() == [0, 1, 2, 6, 8]
    wide = {w: [f for f in range(net.filters) if f // 3 == i] for i, w in enumerate(bytecnn.WIDTHS)}
    assert all(not net.p["W"][w * bytecnn.EMB :, wide[w]].any() for w in wide)


def test_training_windows_are_spread_over_the_whole_text():
    from skewjoin.llm import bytecnn

    texts = ["", "abc", "".join(chr(97 + i // 100) for i in range(2000))]
    raw, off = wordhash.buffers(pa.array(texts))
    win, own = bytecnn.training_windows(raw, off, 100, 5)
    assert np.bincount(own).tolist() == [1, 1, 5] and win.shape[1] == 100 + bytecnn.WIDTH
    assert not win[0].any() and bytes(win[1][:4]) == b"abc\0" and bytes(win[2][:2]) == b"aa" and bytes(win[6][:100]).endswith(b"t")


def test_copies_invert_the_cumulative_demand(spark):
    """Every copy stands where the source's integrated demand meets the middle of its words; found by bisection."""
    from skewjoin.llm import mixing

    rng = random.Random(8)
    rows = [(i, "w " * rng.randrange(0, 30), rng.choice(["a", "b", "b", "c", "c", "c", "c", None])) for i in range(150)] + [(None, "lost words here", "a")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    mixed = mixing.curriculum(docs, share=2.0)
    plan = {r["doc_id"]: r for r in mixed.collect()}
    seen = Counter()
    for r in mixing.copies(mixed).collect():
        m = plan[r["doc_id"]]
        words = min(m["size"], m["taken"] - r["copy"] * m["size"])
        middle = m["start"] + r["copy"] * m["source_size"] + words / 2
        low, high = 0.0, 1.0
        for _ in range(60):
            t = (low + high) / 2
            low, high = (t, high) if m["target"] * ((1 - m["slope"]) * t + m["slope"] * t * t) < middle else (low, t)
        assert abs(low - r["position"]) < 1e-6
        seen[r["doc_id"]] += words
    assert seen == Counter({i: m["taken"] for i, m in plan.items() if m["taken"]})
    out = mixing.mixture(docs, share=2.0)
    assert out.columns == docs.columns
    assert Counter(r["doc_id"] for r in out.collect()) == Counter(r["doc_id"] for r in mixing.copies(mixed).collect())
    order = [r["doc_id"] for r in out.collect()]
    assert order == [r["doc_id"] for r in mixing.copies(mixed).collect()] and None in order


@pytest.mark.parametrize("dim", [16, 32, 64, 256])
def test_embedding_recall_in_other_dimensions(spark, dim):
    rng = np.random.default_rng(dim)
    centre = rng.normal(size=(60, dim))
    x = np.concatenate([centre[rng.integers(0, 60, 500)] + rng.normal(size=(500, dim)) * rng.choice([0.1, 0.25, 0.33], (500, 1)), rng.normal(size=(400, dim))])
    df = spark.createDataFrame([(int(i), [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<double>").repartition(4)
    got = {r["vec_id"]: r["n_links"] for r in embdup.near_vectors(df).collect()}
    u = x / np.linalg.norm(x, axis=1)[:, None]
    near = u @ u.T >= 0.9
    np.fill_diagonal(near, False)
    assert sum(got.values()) >= 0.98 * near.sum() and all(got[i] <= near[i].sum() for i in range(len(x)))
    codes = embdup.learn_rotation(u).codes(u)
    keys = [(t, int(c) >> 16 * t & 0xFFFF) for t in range(4) for c in codes[500:]]
    assert Counter(keys).most_common(1)[0][1] < 120  # the buckets tell vectors apart


# ---- the pipeline against the stages' definitions ----


def test_pipeline_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    steps = dict(corpus_pipeline.STAGES)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "near_dedup", "substring_dedup", "mixing", "sentencepiece"]
    from skewjoin.llm.common import stage

    one = stage(steps["language_id"](spark, docs, small), "t")
    assert one.columns == docs.columns and one.count() >= 0.95 * docs.count()
    rows = {r["doc_id"]: r["text"] for r in one.collect()}
    two = stage(steps["near_dedup"](spark, one, small), "t")
    roots = brute_components(list(rows.items()), 5, 80)
    assert sorted(r["doc_id"] for r in two.collect()) == sorted(i for i, (_, c) in roots.items() if c == i)
    three = stage(steps["substring_dedup"](spark, two, small), "t")
    kept = [(r["doc_id"], r["text"]) for r in two.collect()]
    want = brute_removal(kept, 13)
    got = {r["doc_id"]: r for r in three.collect()}
    assert {i: r["text"].split() for i, r in got.items()} == want and all(r["n_chars"] == len(r["text"]) for r in got.values())
    four = stage(steps["mixing"](spark, three, small), "t")
    times = Counter(r["doc_id"] for r in four.collect())
    assert four.columns == docs.columns and max(times.values()) <= 3
    five = steps["sentencepiece"](spark, four, small).collect()
    assert Counter(r["doc_id"] for r in five) == times
    vocab = sptok.load()
    text = {r["doc_id"]: r["text"] for r in four.collect()}
    assert all(vocab.decode(np.array(r["ids"], dtype=np.int64)).decode() == text[r["doc_id"]] and r["n_pieces"] == len(r["ids"]) for r in five)
    assert corpus_pipeline.ORACLE_SQL is None
