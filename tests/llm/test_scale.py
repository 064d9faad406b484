"""Embeddings without links stay apart, however many there are."""

import numpy as np

from skewjoin.llm import embdup, grouping


def test_unrelated_vectors_form_no_clusters(spark, monkeypatch):
    x = np.random.default_rng(3).normal(size=(12_000, 64)).astype(np.float32)
    x[11_000:11_500] = x[:500] + 0.02 * x[500:1000]  # links of two
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>").repartition(8)
    compared, clusters = [], embdup.open_clusters

    def watched(*args):
        out = clusters(*args)
        compared.append(out.count())
        return out

    monkeypatch.setattr(embdup, "open_clusters", watched)
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embdup.near_vectors(rows).collect()}
    assert got == {i: (int(i < 500 or 11_000 <= i < 11_500), i - 11_000 if 11_000 <= i < 11_500 else i) for i in range(len(x))}
    assert compared == [0]  # chance pairs of codes would join thousands, to be compared one with another


def test_pairwise_forest_is_that_of_prim():
    rng = np.random.default_rng(4)
    base = rng.normal(size=(40, 64))
    unit = base[rng.integers(0, 40, 300)] + 0.15 * rng.normal(size=(300, 64))
    sig = np.column_stack([embdup.sketches(unit), np.full(300, 64, dtype=np.uint64)])
    cut = embdup.least_similar(0.9)
    sums = []
    for forest in (grouping._pairwise, grouping._prim):
        pairs = forest(sig, embdup.hamming_similarity, cut, 1.0)
        s = embdup.hamming_similarity(sig[[a for a, _ in pairs]], sig[[b for _, b in pairs]])
        sums.append((len(pairs), round(float(s.sum()), 9), s.min() >= cut))
    assert sums[0] == sums[1] and sums[0][2]
