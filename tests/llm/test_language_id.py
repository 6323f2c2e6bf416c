import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from annspark.llm import language_id as L

SMALL = "/root/testdata/sf0.01"


def brute(scores, penalty):
    n, k = scores.shape
    return max(sum(scores[t, p[t]] for t in range(n)) - penalty * sum(a != b for a, b in zip(p, p[1:])) for p in itertools.product(range(k), repeat=n))


def test_viterbi_is_optimal():
    rng = np.random.default_rng(1)
    for _ in range(30):
        s = -rng.exponential(3, (6, 3))
        path = L.viterbi(s, 4.0)
        value = s[np.arange(6), path].sum() - 4.0 * (np.diff(path) != 0).sum()
        assert value == pytest.approx(brute(s, 4.0))


def test_monolingual_proof_agrees_with_viterbi():
    model = L.Model([("a", w, 5) for w in ("alpha", "beta", "gamma")] + [("b", w, 5) for w in ("uno", "dos", "tres")])
    rng = np.random.default_rng(2)
    words = ["alpha", "beta", "gamma", "uno", "dos", "tres", "zzz"]
    for _ in range(200):
        text = " ".join(rng.choice(words, rng.integers(1, 30), p=[0.3, 0.2, 0.2, 0.1, 0.05, 0.05, 0.1]))
        lab = L.Labeller(model, penalty=6.0)
        _, _, path, at = lab.label(text)
        scores = lab.table[lab.rows(text.split())]
        best = L.viterbi(scores, 6.0)
        cost = lambda p: scores[np.arange(len(p)), p].sum() - 6.0 * (np.diff(p) != 0).sum()
        assert cost(path) == pytest.approx(cost(best), abs=1e-3)


def test_monolingual_proof_with_three_languages():
    lab = L.Labeller(L.Model([(lang, lang * 3, 5) for lang in "abc"]), penalty=12.0)
    lab.rows = lambda tokens: np.arange(len(tokens))
    rng = np.random.default_rng(5)
    cases = [np.array([(0, -6, -2.9)] * 3 + [(-6, 0, -2.9)] * 3)] + [-rng.exponential(4, (8, 3)) for _ in range(300)]
    for scores in cases:
        lab.table, lab.letters, lab.known = np.float32(scores), np.ones(len(scores), np.int64), np.ones(len(scores), bool)
        path = lab.label("w " * len(scores))[2]
        cost = lambda p: scores[np.arange(len(p)), p].sum() - 12.0 * (np.diff(p) != 0).sum()
        assert cost(path) == pytest.approx(cost(L.viterbi(np.float32(scores), 12.0)), abs=1e-3)
    assert lab.model.langs == ["a", "b", "c"]


def test_mixed_spans_and_scripts():
    model = L.Model([("en", w, 9) for w in ("the", "house", "water", "green")] + [("ru", w, 9) for w in ("дом", "вода", "зеленый")] + [("de", w, 9) for w in ("das", "haus", "wasser", "grün")])
    text = "the house the water the green " * 3 + "дом вода зеленый дом"
    lab = L.Labeller(model)
    spans = lab.spans(text)
    assert [s[2] for s in spans] == ["en", "ru"] and text[spans[1][0] : spans[1][1]] == "дом вода зеленый дом"
    assert lab.label("日本語")[:2] == (model.langs[model.prior], 0.0)
    assert L.script_of("д") == "cyrillic" and L.script_of("a") == "latin" and L.script_of("1") == "other"


def test_only_letters_count():
    lab = L.Labeller(L.Model([("en", w, 9) for w in ("the", "house")]))
    for t in ("²", "½", "Ⅷ", "①", "１２", "_-_", "a²"[1:], "\u0301"):
        assert lab.label(t)[:2] == ("und", 0.0), t
    assert lab.label("²the½")[:2] == ("en", 1.0) and lab.label("日")[0] == "en"


def test_every_word_of_the_sample_counts(docs_of):
    long = "ab" * 40
    model = L.fit(docs_of([(0, f"{long} {long} short", "en", "s")] + [(i, "another text", "en", "s") for i in range(1, 9)]))
    assert long in model.words and model.langs == ["en"]
    many = L.fit(docs_of([(i, "some words", f"label{i % 5}", "s") for i in range(60)]), languages=3)
    assert len(many.langs) == 3


def test_held_out_accuracy(spark):
    got = L.op2_language_id(spark, SMALL).join(spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out")
    share = got.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double"))).first()[0]
    assert share >= 0.97


def test_held_out_rows_follow_the_checksum(spark):
    import zlib

    ids = spark.range(50).select(F.col("id"), L.is_held_out(F.col("id")).alias("out")).collect()
    assert all(r.out == (zlib.crc32(str(r.id).encode()) % 4 == 2) for r in ids)


def test_edges(edge, empty, spark):
    model = L.fit(edge)
    rows = {(r.doc_id, r.lang_pred) for r in L.predict(edge, model).collect()}
    assert {(1, "und"), (2, "und"), (3, "und")} <= rows and len(rows) == 9
    assert all(0 <= r.score <= 1 for r in L.predict(edge, model).collect())
    assert L.predict(empty, L.fit(empty)).count() == 0
    assert {r.lang_pred for r in L.predict(edge, L.Model([])).collect()} == {"und"}
    kept = L.keep_identified(edge, model)
    assert kept.columns == edge.columns and kept.where("doc_id IN (1, 2, 3)").count() == 0 and kept.where("doc_id = 5").count() == 2
