import math

import numpy as np
import pyarrow.parquet as pq
import pytest

from annspark.llm import cross_polytope as X
from annspark.llm import maxscore as M
from annspark.llm import vector_blocks as B
from annspark.operators import grid

SCHEMA = "vec_id long, embedding array<float>, label int, score string, query_id int"


def make(spark, rows):
    return spark.createDataFrame([(i, v, 1, "s", 2) for i, v in rows], SCHEMA)


def valid(v, nonzero=False):
    return v is not None and len(v) > 0 and all(x is not None and math.isfinite(x) for x in v) and (not nonzero or any(x != 0 for x in v))


def rows_for(n, d, seed, ties=True):
    rng = np.random.default_rng(seed)
    out = [(i, np.float32(rng.normal(size=d)).tolist()) for i in range(n)]
    if ties:
        out += [(n + i, out[3][1]) for i in range(40)] + [(5, out[5][1])]
    out += [(10_000, None), (10_050, [None] * d), (10_100, [float("nan")] * d), (10_150, [float("inf")] + [0.0] * (d - 1)), (10_200, [0.0] * d), (10_250, []), (10_300, [1.0, 2.0]), (None, [1.0] * d)]
    return out


@pytest.mark.parametrize("d", [3, 16])
def test_maxscore_is_exact(spark, folder_of, d):
    rows = rows_for(400, d, d)
    got = sorted(tuple(r) for r in M.op9_maxscore_top_k(spark, folder_of("embeddings", make(spark, rows))).collect())
    good = [(i, [math.floor(256 * float(x)) for x in v]) for i, v in rows if i is not None and valid(v)]
    want = []
    for q, v in good:
        if q % 50 == 0:
            hits = sorted((-sum(a * b for a, b in zip(v, w)), i) for i, w in good if i != q and len(w) == len(v))[:5]
            want += [(q, r, i, -s) for r, (s, i) in enumerate(hits, 1)]
    assert got == sorted(want)


def test_maxscore_with_large_values(spark):
    rows = make(spark, [(i, [1e4 * (i - 3), 2e4 * i, -1e4]) for i in range(0, 120, 2)])
    got = M.top_k(M.integer_vectors(rows), M.integer_vectors(rows).where("vec_id = 50")).collect()
    v = {r.vec_id: [math.floor(256 * x) for x in r.embedding] for r in rows.collect()}
    want = sorted((-sum(a * b for a, b in zip(v[50], w)), i) for i, w in v.items() if i != 50)[:5]
    assert [(r.vec_id, r.score) for r in sorted(got, key=lambda r: r["rank"])] == [(i, -s) for s, i in want]


@pytest.mark.parametrize("sf", ["sf0.01", "sf0.1"])
def test_cross_polytope_recall_and_scores(spark, sf):
    folder = f"/root/testdata/{sf}"
    t = pq.read_table(f"{folder}/embeddings.parquet")
    ids, x = t["vec_id"].to_numpy(), np.stack(t["embedding"].to_numpy()).astype(float)
    norm = np.linalg.norm(x, axis=1)
    at = {i: k for k, i in enumerate(ids.tolist())}
    found: dict = {}
    for r in X.op10_cross_polytope(spark, folder).collect():
        found.setdefault(r.query_id, {})[r.vec_id] = r.score
        assert r.score == pytest.approx(float(x[at[r.query_id]] @ x[at[r.vec_id]] / norm[at[r.query_id]] / norm[at[r.vec_id]]), abs=1e-12)
    hits = []
    for q in np.flatnonzero(ids % 50 == 0):
        s = x @ x[q] / norm / norm[q]
        s[q] = -9
        hits.append(len(set(ids[np.lexsort((ids, -s))[:5]]) & set(found[ids[q]])) / 5)
    assert np.mean(hits) >= 0.9
    share = {r.query_id: r.n_candidates / len(ids) for r in X.op10_cross_polytope(spark, folder).collect()}
    assert 0 < np.mean(list(share.values())) <= 0.2


def test_many_blocks_and_shards(spark, monkeypatch):
    monkeypatch.setattr(grid, "QUERY_BLOCK", 7)
    monkeypatch.setattr(grid, "SHARD_ROWS", 40)
    rows = make(spark, rows_for(300, 8, 6))
    ints, reals = M.integer_vectors(rows), B.valid_vectors(rows, nonzero=True)
    cells = grid.grid(ints.where("vec_id % 5 = 0").distinct(), ints).select("block", "shard").distinct().count()
    assert cells > 40
    got = sorted(tuple(r) for r in M.top_k(ints, ints.where("vec_id % 5 = 0")).collect())
    good = [(r.vec_id, r.embedding) for r in ints.collect()]
    want = []
    for q, v in {q: v for q, v in good if q % 5 == 0}.items():
        hits = sorted((-int(np.dot(v, w)), i) for i, w in good if i != q and len(w) == len(v))[:5]
        want += [(q, r, i, -s) for r, (s, i) in enumerate(hits, 1)]
    assert got == sorted(want)
    found = sorted(tuple(r) for r in X.nearest(reals, reals.where("vec_id % 5 = 0")).collect())
    monkeypatch.undo()
    assert found == sorted(tuple(r) for r in X.nearest(reals, reals.where("vec_id % 5 = 0")).collect()) and len(found) == len(got) - 5


def test_copies_tie_by_id(spark, folder_of):
    rows = rows_for(300, 8, 2) + [(20_000 + i, [1.0] * 8) for i in range(200)] + [(50_000, [2.0] * 8)]
    got = [r for r in X.op10_cross_polytope(spark, folder_of("embeddings", make(spark, rows))).collect()]
    near = sorted((r["rank"], r.vec_id) for r in got if r.query_id == 50_000)
    assert near == [(i + 1, 20_000 + i) for i in range(5)]
    assert not {r.vec_id for r in got} & {10_000, 10_050, 10_100, 10_150, 10_200, 10_250}


def test_transform_is_orthogonal():
    x = np.random.default_rng(1).normal(size=(5, 16)).astype(np.float32)
    y = np.stack(list(X.rotated(x, 3)))
    assert np.allclose(np.linalg.norm(y, axis=2), 1, atol=1e-5) and not np.allclose(y[0], y[1])
    assert np.allclose(X.hadamard(X.hadamard(np.eye(8))), 8 * np.eye(8))
    x = np.random.default_rng(2).normal(size=(20, 16))
    y = np.abs(np.stack(list(X.rotated(x, 4))))
    code, probe = X.codes(x, 2), X.probes(x, 2, 10)
    assert (code == probe[:, :, 0]).all()
    for t in range(2):
        for r in range(20):
            sums = np.sort((y[2 * t, r][:, None] + y[2 * t + 1, r][None, :]).ravel())[::-1]
            of = [y[2 * t, r][p // 32 // 2] + y[2 * t + 1, r][p % 32 // 2] for p in probe[t, r]]
            assert len(set(probe[t, r].tolist())) == 10 and np.allclose(of, sums[:10])


@pytest.mark.parametrize("run", [M.op9_maxscore_top_k, X.op10_cross_polytope])
def test_no_rows(spark, folder_of, run):
    assert run(spark, folder_of("embeddings", make(spark, []))).count() == 0
    assert run(spark, folder_of("embeddings", make(spark, [(50, [1.0, 0.0])]))).count() == 0
    got = run(spark, folder_of("embeddings", make(spark, [(50, [1.0, 0.5]), (51, [0.5, 1.0]), (51, [0.5, 1.0])]))).collect()
    assert [(r["rank"], r.vec_id) for r in sorted(got)] == [(1, 51), (2, 51)]


def test_cross_polytope_completes_short_results(spark, folder_of):
    rng = np.random.default_rng(4)
    v = [1.0, 0.5, -2.0, 0.25]
    rows = [(50, v), (51, [-x for x in v])]
    got = X.op10_cross_polytope(spark, folder_of("embeddings", make(spark, rows))).collect()
    assert [(r["rank"], r.vec_id, round(r.score, 12)) for r in got] == [(1, 51, -1.0)]
    # Lengths with few rows beside a long one: every candidate of the length, or the five best of all.
    rows += [(i, (-np.abs(rng.normal(size=16)) if i % 50 else np.abs(rng.normal(size=16))).tolist()) for i in range(100, 300)]
    rows += [(i, rng.normal(size=8).tolist()) for i in range(300, 304)] + [(i, [(-1.0) ** (i > 350)] * 3) for i in range(350, 359)]
    found: dict = {}
    for r in X.op10_cross_polytope(spark, folder_of("embeddings", make(spark, rows).repartition(7))).collect():
        found.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    cos = lambda a, b: float(np.dot(a, b) / np.linalg.norm(a) / np.linalg.norm(b))
    for q, w in rows:
        if q % 50 == 0:
            hits = sorted((-round(cos(np.float32(w), np.float32(x)), 9), i) for i, x in rows if i != q and len(x) == len(w))[:5]
            got = sorted(found[q])
            assert [g[0] for g in got] == list(range(1, min(5, len(hits)) + 1))
            if len(w) < 16:
                assert [g[1] for g in got] == [i for _, i in hits]
