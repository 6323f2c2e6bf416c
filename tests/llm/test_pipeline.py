import hashlib

import numpy as np
import sentencepiece

import corpus_pipeline
from annspark.llm import language_id, registry, secrets, sentencepiece_codec, simhash
from annspark.plans.session import stage

SMALL = "/root/testdata/sf0.001"
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages_one_by_one(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    seen = {}
    for name, step in corpus_pipeline.STAGES:
        out = stage(step(spark, docs, SMALL), f"test-{name}")
        seen[name] = (docs, out)
        if name != corpus_pipeline.STAGES[-1][0]:
            assert out.columns == COLUMNS
        docs = out
    before, after = seen["language_id"]
    model = language_id.fit(before)
    lab = language_id.Labeller(model)
    assert {r.doc_id for r in after.collect()} == {r.doc_id for r in before.collect() if (g := lab.label(r.text))[0] != "und" and g[1] >= language_id.KEEP_SCORE}
    assert after.count() >= 0.95 * before.count()
    before, after = seen["near_duplicates"]
    rows = sorted((r.doc_id, simhash.fingerprint(r.text)) for r in before.collect())
    low = {i: min(j for j, g in rows if (f ^ g).bit_count() <= 2) for i, f in rows}
    kept = {r.doc_id for r in after.collect()}
    assert {i for i, j in low.items() if i == j} >= kept and len(kept) == after.count() > 0.8 * len(rows)
    before, after = seen["secrets"]
    assert before.count() == after.count()
    old, new = ({r.doc_id: r.text for r in x.collect()} for x in (before, after))
    marked = {i for i in old if old[i] != new[i]}
    assert marked and all("[SECRET]" in new[i] for i in marked) and not any("AKIA" in t for t in new.values())
    before, after = seen["mixing"]
    assert {r.doc_id for r in after.collect()} <= {r.doc_id for r in before.collect()}
    docs, out = seen["sentencepiece"]
    lib = sentencepiece.SentencePieceProcessor(model_file=sentencepiece_codec.default_model_path())
    digest = lambda t: hashlib.sha256(np.array(lib.encode(t, add_bos=True, add_eos=True), "<u4").tobytes()).hexdigest()
    assert sorted((r.doc_id, digest(r.text)) for r in docs.collect()) == sorted((r.doc_id, r.ids_sha256) for r in out.collect())


def test_run_is_deterministic(spark):
    first, again = (sorted(tuple(r) for r in corpus_pipeline.run(spark, SMALL).collect()) for _ in range(2))
    assert first == again and first


def test_registry_has_each_operator():
    assert sorted(int(n[2:].split("_")[0]) for n in registry.QUERIES if n.startswith("op")) == list(range(1, 11))
    assert secrets.MARKS["random"] == "[SECRET]" and registry.ORACLES


def test_edge_and_empty_tables(spark, edge, empty, folder_of):
    got = corpus_pipeline.run(spark, folder_of("documents", edge)).collect()
    assert {r.doc_id for r in got} <= {4, 5, 6, 7, 8, None} and got
    assert corpus_pipeline.run(spark, folder_of("documents", empty)).count() == 0


def test_registered_sql_gives_the_same_rows(spark):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "conversations", "embeddings"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SMALL}/{t}.parquet'")
    for name, sql in registry.ORACLES.items():
        got, want = registry.QUERIES[name](spark, SMALL), con.sql(sql)
        cols = sorted(got.columns)
        rows = sorted(([r[c] for c in cols] for r in got.collect()), key=str)
        assert cols == sorted(want.columns) and rows == sorted(([r[want.columns.index(c)] for c in cols] for r in want.fetchall()), key=str), name
