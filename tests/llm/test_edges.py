"""Hard rows for every operator: nulls, empty and very long texts, ties, repeated rows, clashing columns, empty tables."""

import pytest
from pyspark.sql import functions as F

from skewjoin.llm import chat, embdup, langid, mixing, neardup, quality, rules, sptok, substr, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, id long, h1 string, key string, class_id int, comp string, size int"
LONG = " ".join(f"word{i % 977}x{i}" for i in range(30_000))
NOSPACE = "abcdefghij" * 3000


def hard_docs(spark):
    base = "the quick brown fox jumps over the lazy dog and runs far away from all the people in the town today"
    rows = [
        (0, base, "en", "a"), (1, base, "en", "a"), (1, base, "en", "a"), (2, None, None, None), (3, "", "en", "b"), (4, " \n\t ", "en", "b"),
        (5, "one", "en", "b"), (6, "one two", None, "b"), (7, LONG, "en", "c"), (8, NOSPACE, "en", "c"), (None, base, "en", None),
        (9, base.upper(), "en", "a"), (10, "été ▁ 日本語 😀 \x00 \x85", "fr", ""), (11, base + " extra", "en", "a"), (12, "12345 67890", "en", "a"),
    ]
    return spark.createDataFrame([(*r, len(r[1] or ""), 1, "x", "y", 2, "z", 3) for r in rows], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark):
    return hard_docs(spark)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def ids(df, col="doc_id"):
    return sorted((r[col] is None, r[col] or 0) for r in df.select(col).collect())


def test_language(docs, empty):
    model = langid.train([("der hund und die katze sind nicht da " * 4, "de"), ("the dog and the cat are not there " * 4, "en")] * 20, epochs=4)
    out = {r["doc_id"]: r for r in langid.predict(docs, model).collect()}
    assert ids(langid.predict(docs, model)) == ids(docs)
    for i in (2, 3, 4, 12):
        assert (out[i]["lang_pred"], out[i]["score"]) == ("und", 0.0)
    assert out[0]["lang_pred"] == "en" and all(0 <= r["score"] <= 1 for r in out.values())
    assert langid.predict(empty, model).count() == 0
    nothing = langid.fit(empty)
    assert {r["lang_pred"] for r in langid.predict(docs, nothing).collect()} == {"und"}
    kept = langid.keep_identified(docs, model, 0.0)
    assert kept.columns == docs.columns and 2 not in {r["doc_id"] for r in kept.collect()}


def test_quality_and_toxicity(docs, empty):
    model = quality.train([("plain words of a calm text " * 8, 1), ("BUY!!! $$$ ### NOW!!! " * 8, 0)] * 20, epochs=4)
    rows = quality.score(docs, model).collect()
    assert sorted(str(r["doc_id"]) for r in rows) == sorted(str(r["doc_id"]) for r in docs.collect()) and all(0 <= r["score"] <= 1 for r in rows)
    assert quality.score(empty, model).count() == 0
    assert {r["score"] for r in quality.score(docs, quality.train([])).collect()} == {0.5}
    calm = [(f"a calm text number {i} about {w} and trees {i * 7} on hills", 0) for i in range(60) for w in ("rivers", "fields")]
    rude = [(f"you are a vile brute number {i} go away {i * 3} vile brute", 1) for i in range(60)]
    tox = toxicity.train(calm + rude, 0.3)
    got = {r["doc_id"]: r["score"] for r in toxicity.score(docs, tox).collect()}
    assert all(0 <= s <= 1 for s in got.values()) and got[2] == got[3] == got[4] == pytest.approx(0.3)
    assert toxicity.score(empty, tox).count() == 0
    assert {r["score"] for r in toxicity.score(docs, toxicity.train([], 0.1)).collect()} == {0.0}


def test_near_duplicates(docs, empty):
    rows = neardup.near_duplicates(docs, 3, 85).collect()
    out = {r["doc_id"]: r for r in rows}
    assert len(rows) == docs.count()
    assert out[0]["component_id"] == out[1]["component_id"] == out[9]["component_id"] == out[11]["component_id"] == 0
    assert out[2]["n_shingles"] == out[3]["n_shingles"] == out[4]["n_shingles"] == 0 and out[5]["n_shingles"] == out[6]["n_shingles"] == 1
    assert out[7]["component_id"] == 7 and out[None]["kept"] and out[None]["component_id"] is None
    assert neardup.near_duplicates(empty).count() == 0
    kept = neardup.drop_near_duplicates(docs, 3, 85)
    assert kept.columns == docs.columns
    assert ids(kept) == sorted((i is None, i or 0) for i in (0, 2, 3, 4, 5, 6, 7, 8, 10, 12, None))


def test_substrings(docs, empty):
    rows = substr.removal_digest(docs).collect()
    out = {r["doc_id"]: r for r in rows}
    assert len(rows) == docs.count()
    n = out[0]["n_words"]
    assert out[0]["n_removed"] == 0 and out[1]["n_removed"] == n and out[11]["n_removed"] == n and out[None]["n_removed"] == 0
    assert out[9]["n_removed"] == 0 and out[2]["n_words"] == 0
    assert substr.removal_digest(empty).count() == 0
    cut = substr.remove_repeats(docs)
    texts = {r["doc_id"]: r["text"] for r in cut.collect()}
    assert cut.columns == docs.columns and texts[1] == "" and texts[11] == "extra" and texts[2] is None and texts[7] == LONG


def test_mixing(docs, empty):
    rows = mixing.curriculum(docs).collect()
    assert len(rows) == docs.count()
    by = {}
    for r in rows:
        by.setdefault(r["source"], [0, r["target"], 0])
        by[r["source"]][0] += r["taken"]
        by[r["source"]][2] += r["size"]
        assert r["taken"] <= 3 * r["size"]
    for taken, target, size in by.values():
        assert abs(taken - target) <= 1 and target <= 3 * size + 1e-9
    assert mixing.curriculum(empty).count() == 0 and mixing.mixture(empty).count() == 0
    assert mixing.mixture(docs).columns == docs.columns
    again = mixing.curriculum(docs).collect()
    assert sorted(map(str, again)) == sorted(map(str, rows))


def test_rules(docs, empty):
    rows = rules.apply_rules(docs).collect()
    out = {r["doc_id"]: r for r in rows}
    assert len(rows) == docs.count() and out[2]["base_failed"] and not out[3]["kept"]
    assert out[0]["n_words"] == 21 and out[7]["n_words"] == 30_000 and out[8]["word_chars"] == 30_000
    assert out[10]["word_chars"] == len("été▁日本語😀\x00\x85")
    assert rules.apply_rules(empty).count() == 0
    base = rules.with_ratios(rules.base_measures(docs))
    whole = rules.sketch(base).exceptAll(rules.merge_sketches(rules.sketch(base.where("doc_id % 2 = 0 or doc_id is null")), rules.sketch(base.where("doc_id % 2 = 1"))))
    assert whole.count() == 0


def test_tokens(docs, empty):
    vocab = sptok.load()
    enc = sptok.encode(docs, vocab)
    back = {r["doc_id"]: r["text"] for r in sptok.decode(enc, vocab).collect()}
    want = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    assert back == want
    assert sptok.encode(docs, vocab, full=False).where("not lossless").count() == 0
    assert sptok.encode(empty, vocab).count() == 0


def test_embeddings(spark):
    nan, inf = float("nan"), float("inf")
    rows = [
        (0, [1.0, 0.0, 0.0]), (1, [2.0, 0.0, 0.0]), (2, [1.0, 0.01, 0.0]), (3, None), (4, [0.0, 0.0, 0.0]), (5, [nan, 1.0, 0.0]), (6, [inf, 1.0, 0.0]),
        (7, [1.0, None, 0.0]), (8, [1.0, 0.0]), (9, [1.0, 0.0]), (10, [0.0, 1.0, 0.0]), (11, []), (None, [1.0, 0.0, 0.0]), (12, None), (13, [1.0, 0.0, 0.0]),
    ]
    df = spark.createDataFrame([(i, v, 1, "x") for i, v in rows], "vec_id long, embedding array<float>, label int, unit string")
    out = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in embdup.near_vectors(df).collect()}
    assert len(out) == len(rows)
    assert out[0] == (3, 0, True) and out[1] == (3, 0, False) and out[2] == (3, 0, False) and out[13] == (3, 0, False)
    for i in (3, 4, 5, 6, 7, 10, 11, 12):
        assert out[i] == (0, i, True), i
    assert out[8] == (1, 8, True) and out[9] == (1, 8, False) and out[None] == (0, None, True)
    assert embdup.near_vectors(df.limit(0)).count() == 0


def test_chat(spark):
    rows = [(1, 0, "user", None), (1, 1, "assistant", "a\\b <|end|> [INST] x </s>"), (1, 1, "assistant", "tie"), (2, 0, None, "<|text|>"), (None, 0, "assistant", "ü😀")]
    df = spark.createDataFrame([(*r, "z") for r in rows], "conv_id long, turn long, role string, text string, message string")
    out = {r["conv_id"]: r for r in chat.digest(chat.render(chat.fold(chat.as_log(df)))).collect()}
    assert out[1]["n_turns"] == 3 and out[1]["loss_chars"] == len("a\\b <|end|> [INST] x </s>" + "tie")
    assert out[2]["n_turns"] == 1 and out[2]["loss_chars"] == 0 and out[None]["loss_chars"] == 2
    assert chat.digest(chat.render(chat.fold(chat.as_log(df.limit(0))))).count() == 0


def test_chat_log_folds_edits_and_regenerations(spark):
    log = [
        (1, 1, 1, "start", "user", None), (1, 2, 1, "delta", None, "Hel"), (1, 3, 1, "delta", None, "lo"), (1, 4, 2, "start", "assistant", None),
        (1, 5, 2, "delta", None, "bad"), (1, 6, 2, "regenerate", None, None), (1, 7, 2, "delta", None, "go"), (1, 8, 2, "delta", None, "od"),
        (1, 9, 1, "edit", None, "Hi"), (1, 10, 1, "delta", None, "!"), (1, 11, 3, "start", "user", None), (1, 12, 3, "delta", None, "gone"), (1, 13, 3, "retract", None, None),
        (1, 14, 4, "start", "user", None),
    ]
    df = spark.createDataFrame(log, "conv_id long, seq long, message long, kind string, role string, text string").repartition(3)
    got = [(r["message"], r["role"], r["text"]) for r in chat.fold(df).orderBy("message").collect()]
    assert got == [(1, "user", "Hi!"), (2, "assistant", "good"), (4, "user", "")]
    one = chat.render(chat.fold(df)).select("formatted", chat.masked(F.col("formatted"), F.col("loss")).alias("m"), chat.parse(F.col("formatted")).alias("p")).first()
    assert one["m"] == "good" and [tuple(t) for t in one["p"]] == [("user", "Hi!"), ("assistant", "good"), ("user", "")]


def test_pipeline_on_hard_rows_and_empty_tables(spark, docs, empty, tmp_path):
    import corpus_pipeline
    from skewjoin.llm.common import stage

    ten = [(100 + i, " ".join(["der hund und die katze sind heute nicht da", "the dog and the cat are not there today"][i % 2].split()[i % 5 :]) + f" wort{i} word{i}", ["de", "en"][i % 2], "s", 1) for i in range(400)]
    more = spark.createDataFrame(ten, "doc_id long, text string, lang string, source string, n_chars long").withColumns({c: F.lit(None).cast(t) for c, t in [("id", "long"), ("h1", "string"), ("key", "string"), ("class_id", "int"), ("comp", "string"), ("size", "int")]})
    for table in (docs.unionByName(more), empty):
        now, n = table, []
        for name, step in corpus_pipeline.STAGES:
            out = stage(step(spark, now, ""), name)
            assert name == "sentencepiece" or out.columns == table.columns
            now = out
            n.append(now.count())
        if table is not empty:
            assert n[0] >= 380 and n[2] == n[1] <= n[0] and n[4] == n[3] > 300
    for name, table in (("full", docs.unionByName(more)), ("none", empty)):
        table.write.parquet(str(tmp_path / name / "documents.parquet"))
        assert (corpus_pipeline.run(spark, str(tmp_path / name)).count() > 0) == (name == "full")
