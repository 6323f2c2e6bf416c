from collections import Counter

import pytest
from pyspark.sql import functions as F

from annspark.llm import token_counts as T

ROWS = [(1, "a b c", "en", "s"), (2, "a b c", "en", "s"), (3, "x-y z", None, "s"), (4, None, "de", None), (5, "", "de", "t"), (6, "hello <|endoftext|> world", "en", "t")]


def totals(df):
    return {(r.source, r.lang, r.tokenizer_version): (r.n_docs, r.n_tokens) for r in df.collect()}


def test_counts_match_brute_force(docs_of, folder_of, spark):
    enc = T._byte_bpe(T.default_ranks_path())
    got = totals(T.op1_token_counts(spark, folder_of("documents", docs_of(ROWS))))
    want: dict = {}
    for i, t, lang, src in ROWS:
        if i == 2:  # an exact copy of 1
            continue
        for v, n in ((T.TERMS, len(T._TERM.findall(t or ""))), (T.BYTE_BPE, len(enc.encode_ordinary(t or "")))):
            a, b = want.get((src, lang, v), (0, 0))
            want[src, lang, v] = (a + 1, b + n)
    assert got == want


def test_batches_commit_once_and_compact(docs_of, spark, tmp_path):
    counted = T.count_tokens(docs_of(ROWS), (T.WORDS,)).cache()
    roll = T.TokenRollup(spark, str(tmp_path / "roll"))
    assert totals(roll.totals()) == {}
    assert roll.commit("b1", T.changes(counted, T.WORDS, 1))
    before = totals(roll.totals())
    assert not roll.commit("b1", T.changes(counted, T.WORDS, 1)) and totals(roll.totals()) == before
    assert roll.commit("b2", T.changes(counted.where("doc_id = 1"), T.WORDS, -1))
    after = totals(roll.totals())
    assert after["s", "en", T.WORDS] == (before["s", "en", T.WORDS][0] - 1, before["s", "en", T.WORDS][1] - 3)
    roll.compact()
    assert totals(roll.totals()) == after
    assert not roll.commit("b1", T.changes(counted, T.WORDS, 1)) and totals(roll.totals()) == after
    assert roll.commit("b3", T.changes(counted.where("doc_id <> 1"), T.WORDS, -1)) and totals(roll.totals()) == {}
    roll.compact()
    assert totals(roll.totals()) == {} and roll.committed() == {"b1", "b2", "b3"}
    with pytest.raises(ValueError):
        roll.commit("../x", counted)


def test_a_batch_that_arrives_during_compaction_is_kept(docs_of, spark, tmp_path, monkeypatch):
    counted = T.changes(T.count_tokens(docs_of(ROWS), (T.WORDS,)), T.WORDS, 1)
    roll = T.TokenRollup(spark, str(tmp_path / "c"))
    roll.commit("b1", counted)
    inner = roll._totals
    monkeypatch.setattr(roll, "_totals", lambda *a: (T.TokenRollup(spark, roll.path).commit("b2", counted), inner(*a))[1])
    roll.compact()
    monkeypatch.undo()
    docs = lambda: sum(n for n, _ in totals(roll.totals()).values())
    assert roll.committed() == {"b1", "b2"} and docs() == 2 * len(ROWS)
    assert not roll.commit("b2", counted) and docs() == 2 * len(ROWS)
    # A writer that looked before another one committed the id, and one that comes after compaction.
    monkeypatch.setattr(roll, "committed", set)
    assert not roll.commit("b2", counted) and roll.commit("b1", counted)
    monkeypatch.undo()
    assert docs() == 2 * len(ROWS)
    roll.compact()
    assert docs() == 2 * len(ROWS) and not [p for p in (tmp_path / "c").iterdir() if p.name.startswith(("attempt", "batch"))]


def test_edges(edge, empty, spark, tmp_path):
    rows = T.count_tokens(edge, (T.WORDS, T.BYTE_BPE)).collect()
    assert len(rows) == 10 and Counter(r[T.WORDS] for r in rows if r.doc_id == 5) == {1: 2}
    assert T.count_tokens(empty, (T.WORDS,)).count() == 0
    roll = T.TokenRollup(spark, str(tmp_path / "e"))
    assert roll.commit("none", T.changes(T.count_tokens(empty, (T.WORDS,)), T.WORDS, 1)) and totals(roll.totals()) == {}


def test_stream_replay(docs_of, spark, tmp_path):
    counted = T.changes(T.count_tokens(docs_of(ROWS), (T.WORDS,)), T.WORDS, 1)
    roll = T.TokenRollup(spark, str(tmp_path / "s"))
    sink = roll.stream_sink("events")
    sink(counted, 0)
    sink(counted, 0)
    assert sum(n for n, _ in totals(roll.totals()).values()) == len(ROWS)


def test_copies_keep_the_smallest_id(docs_of):
    counted = T.count_tokens(docs_of(ROWS), (T.WORDS,))
    assert [r.doc_id for r in T.exact_copies(counted).select(F.col("doc_id")).collect()] == [2]
