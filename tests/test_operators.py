import struct
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from annspark import catalogue, experiments
from annspark.functions import graphs as G
from annspark.functions.graphs import Params
from annspark.functions.rules import ScaledShiftedBall, ShiftedBall, UnitBall
from annspark.operators import build, exact, grid, measures, search, theory
from annspark.plans import query_plan
from annspark.plans.session import stage
from annspark.sources import vectors as V
from annspark.sources.store import IndexStore
from annspark.sources.vector_files import VectorFiles
from annspark.streaming import serving


def frame(spark, x, first=0):
    return spark.createDataFrame([(first + i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")


def points(n=200, d=3, seed=0):
    return np.random.default_rng(seed).normal(size=(n, d))


@pytest.mark.parametrize("rule", [UnitBall(), ShiftedBall(0.05), ScaledShiftedBall(1.2, 0.05)])
def test_sql_and_arrow_forms_agree(spark, rule):
    p = frame(spark, points(60))
    key = lambda df: sorted((r.src, r["rank"], r.dst, round(r.dist, 9)) for r in df.collect())
    assert key(build.full_graph(p, rule)) == key(build.full_graph_sql(p, rule))


def test_full_graph_is_limited(spark):
    with pytest.raises(ValueError):
        build.full_graph(frame(spark, points(30)), UnitBall(), limit=20)


def test_exact_search_over_partitions_and_blocks(spark, monkeypatch):
    x, q = points(300), points(40, seed=2)
    monkeypatch.setattr(grid, "QUERY_BLOCK", 16)
    monkeypatch.setattr(grid, "SHARD_ROWS", 50)
    asked = exact.as_queries(frame(spark, q, 1000))
    for parts, rows in ((1, 10_000), (5, 10_000), (2, 7), (1, 2)):
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)
        got = exact.exact_knn(frame(spark, x).repartition(parts), asked, 4).collect()
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
        for i, row in enumerate(q):
            d = np.sqrt(((x - row) ** 2).sum(1))
            assert [r.vec_id for r in sorted(got, key=lambda r: r["rank"]) if r.q_id == 1000 + i] == np.argsort(d)[:4].tolist()
    assert exact.exact_knn(frame(spark, x).limit(0), asked, 4).count() == 0 and exact.exact_knn(frame(spark, x), asked.limit(0), 4).count() == 0


def test_range_join_finds_all_pairs(spark):
    x = points(150, 2)
    got = {(r.l_id, r.r_id) for r in exact.range_join(frame(spark, x), frame(spark, x), 0.2).collect()}
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    assert got == {(int(a), int(b)) for a, b in zip(*np.nonzero(d <= 0.2))}


def test_indexes_do_not_depend_on_partitions(spark):
    p = frame(spark, points(150))
    rows = [sorted((r.src, tuple(r.nbrs)) for r in build.build_index(p.repartition(n), "lcg_adaptive", Params(K=10, M=8, L=12, C=40)).collect()) for n in (1, 4, 16)]
    assert rows[0] == rows[1] == rows[2]


def test_shards_with_all_probes_are_exact(spark):
    x = points(400, 2)
    p = frame(spark, x)
    asked = exact.as_queries(frame(spark, points(20, 2, 5), 5000))
    router = build.train_router(p, 4)
    index = stage(build.build_index(p, "lcg_adaptive", Params(K=10, M=8, L=12, C=40), router, rho=0.2), "t")
    assert index.select("shard").distinct().count() == 4
    found = search.search_index(index, asked, 5, [400], router, 4)
    want = sorted((r.q_id, r.vec_id) for r in exact.exact_knn(p, asked, 5).collect())
    assert sorted((r.q_id, r.vec_id) for r in found.select("q_id", "vec_id").collect()) == want
    radii = search.shard_radii(index, router)
    near = exact.exact_knn(p, asked, 1)
    far = near.agg(F.max("dist")).first()[0]
    only = search.search_index(index, asked, 1, [400], router, 1, tau=far, radii=radii)  # every shard a ball touches
    assert sorted((r.q_id, r.vec_id) for r in only.select("q_id", "vec_id").collect()) == sorted((r.q_id, r.vec_id) for r in near.collect())


def test_supersteps_equal_the_kernel(spark):
    p = frame(spark, points(60))
    index = stage(build.build_index(p, "lcg_adaptive", Params(K=8, M=6, L=8, C=20)), "t")
    asked = exact.as_queries(frame(spark, points(3, seed=8), 900))
    kernel = {(r.q_id, r.vec_id, r.ndc, r.hops) for r in search.search_index(index, asked, 3, [4]).collect()}
    assert {(r.q_id, r.vec_id, r.ndc, r.hops) for r in search.bsp_search(index, asked, 3, 4).collect()} == kernel


def test_refined_graph_is_close_to_exact(spark):
    p = stage(frame(spark, points(250)), "t")
    got = measures.graph_recall(build.nn_descent(p, 10), build.nn_descent(p, 10).limit(0).union(exact.exact_knn_graph(p, 10)), 10).first()[0]
    assert got >= 0.95


def test_measures_on_worked_numbers(spark):
    truth = spark.createDataFrame([(1, 1, 10, 1.0), (1, 2, 11, 2.0), (2, 1, 20, 4.0), (2, 2, 21, 5.0)], "q_id long, rank int, vec_id long, dist double")
    found = spark.createDataFrame([(1, 10, 1.0), (1, 12, 3.0)], "q_id long, vec_id long, dist double")
    assert sorted((r.q_id, r.recall) for r in measures.recall_at_k(found, truth, 2).collect()) == [(1, 0.5), (2, 0.0)]
    assert sorted((r.q_id, r.ratio) for r in measures.approx_ratio(found, truth).collect()) == [(1, 1.0), (2, None)]
    assert {r.tau: r.share for r in measures.tau_coverage(truth, [1.0, 4.0]).collect()} == {1.0: 0.5, 4.0: 1.0}
    curves = spark.createDataFrame([("a", 0.8, 100.0, 10.0), ("a", 1.0, 200.0, 20.0), ("b", 0.85, 50.0, 30.0), ("b", 0.95, 150.0, 40.0)], "method string, recall double, ndc double, hops double")
    got = {r.measure: (r.ours, r.value, r.speedup) for r in measures.speedup_at_recall(curves, 0.9, "a", ("b",)).collect()}
    assert got["ndc"] == pytest.approx((150, 100, 2 / 3)) and got["hops"] == pytest.approx((15, 35, 35 / 15))


def test_rings_at_their_borders(spark):
    pairs = spark.createDataFrame([(0, 1, 8.0), (0, 2, 4.0), (0, 3, 1.0), (0, 4, 5.0), (0, 5, 0.9)], "src long, dst long, dist double")
    assert {r.ring: r.n for r in measures.ring_histogram(pairs, 8.0).collect()} == {0: 2, 1: 1, 3: 2}


def test_hygiene(spark):
    rows = [(1, [1.0, 2.0]), (2, [1.0, 2.0]), (3, None), (4, [float("nan"), 1.0]), (5, [1.0]), (None, [0.0, 0.0]), (6, [3.0, None]), (7, [0.5, 0.5])]
    good, bad = V.sanitize(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    assert sorted(r.vec_id for r in good.collect()) == [1, 2, 7] and bad.count() == 5
    assert sorted((r.vec_id, r.copies) for r in V.collapse_duplicates(good).collect()) == [(1, 2), (7, 1)]


def test_store_versions_updates_and_rebuild(spark, tmp_path):
    x = points(120)
    store = IndexStore(spark, str(tmp_path / "ix"))
    assert store.versions() == []
    assert store.write(frame(spark, x), "lcg_adaptive", Params(K=10, M=8, L=12, C=40)) == 1
    asked = exact.as_queries(frame(spark, x[:5] + 1e-4, 900))
    first = lambda: {r.q_id: r.vec_id for r in store.search(asked, 3, 120).where("rank = 1").collect()}
    assert first() == {900 + i: i for i in range(5)}
    store.insert(frame(spark, x[:1] + 1e-4, 5000))
    store.delete(spark.createDataFrame([(1,)], "vec_id long"))
    now = first()
    assert now[900] == 5000 and now[901] != 1 and now[902] == 2
    assert store.rebuild() == 2 and first() == now and store.versions() == [1, 2] and store.live_delta().count() == 0


def test_planner_chooses_and_answers(spark):
    x = points(500)
    p = frame(spark, x).withColumn("tag", (F.col("vec_id") % 10).cast("int"))
    index = stage(build.build_index(p, "lcg_adaptive", Params(K=12, M=10, L=15, C=60)), "t")
    asked = exact.as_queries(frame(spark, points(6, seed=4), 9000))
    wanted = {"scan": (None, 400), "probe": (None, 100), "pre_filter": (F.col("tag") == 3, 20), "post_filter": (F.col("tag") < 8, 20)}
    for how, (pred, width) in wanted.items():
        got, rows = query_plan.answer(query_plan.AnnQuery(5, width, pred), p, index, asked)
        truth = exact.exact_knn(p if pred is None else p.where(pred), asked, 5)
        assert got == how and rows.count() == 30
        assert measures.recall_at_k(rows, truth, 5).agg(F.avg("recall")).first()[0] >= 0.9


@pytest.mark.parametrize("kind", ["fvecs", "bvecs", "ivecs"])
def test_vector_files(spark, tmp_path, kind):
    x = np.arange(70).reshape(10, 7)
    types = {"fvecs": "<f4", "bvecs": "u1", "ivecs": "<i4"}
    (tmp_path / f"a.{kind}").write_bytes(b"".join(struct.pack("<i", 7) + r.astype(types[kind]).tobytes() for r in x))
    spark.dataSource.register(VectorFiles)
    df = spark.read.format("vecs").option("rowsPerPartition", 3).load(str(tmp_path / f"*.{kind}"))
    assert df.rdd.getNumPartitions() == 4 and [r.embedding for r in df.orderBy("vec_id").collect()] == x.astype(float).tolist()


def test_streams(spark, tmp_path):
    x = points(100)
    index = stage(build.build_index(frame(spark, x), "lcg_adaptive", Params(K=10, M=8, L=12, C=40)), "t")
    asked = exact.as_queries(frame(spark, x[:8] + 1e-5, 900))
    asked.repartition(2).write.parquet(str(tmp_path / "in"))
    for _ in range(2):  # a second run finds nothing new
        stream = serving.stream_of(spark, str(tmp_path / "in"), asked.schema)
        serving.answer_stream(stream, index, 1, 10, str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination()
    rows = spark.read.parquet(str(tmp_path / "out")).collect()
    assert sorted((r.q_id, r.vec_id) for r in rows) == [(900 + i, i) for i in range(8)]
    spark.createDataFrame([(0, i, False) for i in range(5)] + [(0, 2, True), (1, 9, False)], "shard int, vec_id long, deleted boolean").coalesce(1).write.parquet(str(tmp_path / "ins"))
    ins = serving.stream_of(spark, str(tmp_path / "ins"), "shard int, vec_id long, deleted boolean")
    run = serving.insert_buffer(ins, 4).writeStream.format("memory").queryName("pending").outputMode("update").trigger(availableNow=True).start()
    run.awaitTermination()
    assert {(r.shard, r.pending, r.flushed) for r in spark.table("pending").collect()} == {(0, 0, 4), (1, 1, 0)}


def test_windows(spark):
    e = spark.sql("SELECT timestamp_seconds(x * 600) AS ts, double(x) AS v FROM (SELECT explode(sequence(0, 11)) AS x)")
    assert [r.n for r in serving.windowed(e, "ts", "v").orderBy("start").collect()] == [6, 6]
    assert serving.windowed(e, "ts", "v", "session").first().n == 12 and serving.windowed(e, "ts", "v", "sliding").count() == 11


def test_rules_behave_as_the_theory_says(spark, small):
    rows = {(r.rule, r.regime): r for r in experiments.rules_compared(spark, "/root/testdata/sf0.01").collect()}
    ours = {k[1]: r for k, r in rows.items() if k[0] == "scaled_shifted"}
    assert ours["in_data"].exact == ours["within_tau"].exact == 1.0 and ours["beyond"].max_ratio <= 11
    assert ours["within_tau"].mean_hops < rows["unit", "within_tau"].mean_hops and rows["unit", "in_data"].exact == 1.0
    assert rows["unit", "in_data"].mean_degree <= rows["scaled", "in_data"].mean_degree <= ours["in_data"].mean_degree


def test_reuse_and_lazy_pruning_save_work(spark, small):
    r = experiments.reuse(spark, small).first()
    assert r.pairs_reused < r.pairs_plain and r.saving > 1.2
    w = {x.method: x.selections for x in experiments.backward(spark, small).collect()}
    assert w["lcg_adaptive"] < w["lcg_adaptive_eager"]


def test_theory_regime_flag():
    assert theory.theory_regime(1.2, 1.0, True, True, False) and not theory.theory_regime(1.2, 0.5, True, True, False)


def test_functions_for_sql(spark):
    from annspark.functions import sqlfns

    x = points(80)
    p = frame(spark, x)
    sqlfns.register(spark)
    sqlfns.register_index(spark, build.build_index(p, "lcg_adaptive", Params(K=8, M=8, L=10, C=30)))
    p.createOrReplaceTempView("pts")
    row = spark.sql("SELECT l2_distance(array(0D, 3D), array(4D, 0D)) AS a, l1_distance(array(0D, 3D), array(4D, 0D)) AS b, chord_distance(array(2D, 0D), array(0D, 5D)) AS c, angular_distance(array(2D, 0D), array(0D, 5D)) AS d, l2_distance(NULL, array(1D)) AS e, unit_norm(array(3D, 4D)) AS f").first()
    assert (row.a, row.b, row.c, row.d, row.e, row.f) == (5.0, 7.0, pytest.approx(2**0.5), pytest.approx(np.pi / 2), None, [0.6, 0.8])
    got = spark.sql("SELECT q.vec_id AS q, t.vec_id AS v FROM pts q, LATERAL ann_topk(q.embedding, 1, 80) t").collect()
    assert len(got) == 80 and all(r.q == r.v for r in got)
    trace = spark.sql("SELECT t.* FROM pts q, LATERAL ann_trace(q.embedding) t WHERE q.vec_id = 5 ORDER BY hop").collect()
    assert all(a.dist > b.dist for a, b in zip(trace, trace[1:]))
    merged = spark.sql("SELECT topk_merge(d, i, 2) AS m FROM VALUES (2D, 7L), (1D, 9L), (1D, 8L) AS t(d, i)").first().m
    assert merged == [8, 9]


def test_staged_tables_can_be_released(spark):
    from annspark.plans import session

    session.release_staged(spark)
    df = session.stage(frame(spark, points(5)), "released")
    assert df.count() == 5 and session.release_staged(spark) == 1 and session.release_staged(spark) == 0


def test_late_rows_are_counted(spark, tmp_path):
    schema = "ts timestamp"
    for i, seconds in enumerate(([0, 10_000], [9_000, 100, 20_000], [])):
        df = spark.createDataFrame([(s,) for s in seconds], "s long").select(F.timestamp_seconds("s").alias("ts")).coalesce(1)
        df.write.mode("append").parquet(str(tmp_path / "in"))
        stream = serving.stream_of(spark, str(tmp_path / "in"), schema)
        serving.count_late(stream, "ts", str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out")).groupBy().agg(F.sum("rows").alias("rows"), F.sum("late").alias("late")).first()
    assert (got.rows, got.late) == (5, 1)


def test_near_rings_hold_no_more_than_their_packing(spark):
    p = frame(spark, points(80, 2))
    pairs = theory.pair_distances(p)
    g = build.full_graph(p, ScaledShiftedBall(1.2, 0.1))
    rows = theory.near_ring_counts(g, pairs, 1.2, 0.1).collect()
    assert rows and all(0 < r.packing and r.kept <= r.packing for r in rows)


def test_near_copies_keep_every_document(spark, tmp_path):
    texts = {1: "a b c d e f g h", 2: "H g f e d c b a", 3: "only copies here", 4: "only copies here", 5: "only  Copies\nhere", 6: "alone", 7: "a b c d e f g h " * 12 + "i", 8: " "}
    spark.createDataFrame(list(texts.items()), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = catalogue.QUERIES["doc_near_copies"](spark, str(tmp_path)).collect()
    assert sorted((r.l_id, r.r_id) for r in got if r.kind == "member") == [(1, 1), (1, 2), (3, 3), (3, 4), (3, 5), (6, 6), (7, 7)]
    assert [(r.l_id, r.r_id) for r in got if r.kind == "near"] == [(1, 7)]


def test_store_asks_again_when_the_nearest_are_deleted(spark, tmp_path):
    x = np.concatenate([np.random.default_rng(2).normal(0, 0.01, (60, 4)), np.random.default_rng(3).normal(5, 1, (40, 4))])
    store = IndexStore(spark, str(tmp_path / "ix"))
    store.write(frame(spark, x), "lcg_adaptive", Params(K=20, M=12, L=30, C=60, alpha=1.1, tau=0.01))
    store.delete(spark.createDataFrame([(i,) for i in range(60)], "vec_id long"))
    asked = spark.createDataFrame([(0, [0.0] * 4), (1, [5.0] * 4)], "q_id long, qvec array<double>")
    got = store.search(asked, 5, 10).collect()
    for q, c in ((0, 0.0), (1, 5.0)):
        want = 60 + np.argsort(np.linalg.norm(x[60:] - c, axis=1), kind="stable")[:5]
        assert [r.vec_id for r in sorted(got, key=lambda r: r["rank"]) if r.q_id == q] == want.tolist()


def test_pair_extremes_and_graphs_have_no_row_limit(spark, monkeypatch):
    monkeypatch.setattr(exact, "PAIR_BLOCK", 64)
    x = np.concatenate([points(300, 4), points(1, 4), points(40, 4)[:5] + 3e-7])
    p = frame(spark, x)
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    got = theory.aspect_ratio(p).first()
    assert got.diameter == pytest.approx(d.max(), abs=1e-12) and got.smallest == pytest.approx(d[d > 0].min(), abs=1e-12) and got.ratio == pytest.approx(d.max() / d[d > 0].min())
    pairs = theory.pair_distances(p).toPandas()
    assert len(pairs) == 306 * 305 and np.allclose(pairs["dist"], d[pairs["src"], pairs["dst"]], atol=1e-12)
    # More points than the limits that were: in two dimensions, as fast as may be.
    wide = frame(spark, points(5100, 2))
    asked = spark.createDataFrame([(1, [0.1, 0.2])], "q_id long, qvec array<double>")
    assert theory.query_distances(wide, asked).count() == 5100 and theory.pair_distances(wide).count() == 5100 * 5099
    few = frame(spark, points(250, 3))
    assert build.full_graph_sql(few, UnitBall()).count() == build.full_graph(few, UnitBall()).count()


def test_statistics_cover_every_row(spark):
    x = points(2600, 2, seed=8)
    p = frame(spark, x)
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    np.fill_diagonal(d, np.inf)
    assert experiments.median_nearest(p) == pytest.approx(np.median(d.min(axis=1)), abs=1e-12)
    # A dense line that the first 2000 rows by hash don't have.
    first = {r.vec_id for r in p.orderBy(F.xxhash64("vec_id"), "vec_id").limit(2000).collect()}
    y = np.zeros((2600, 64))
    rest = [i for i in range(2600) if i not in first]
    y[sorted(first), 0] = np.linspace(0, 1e-3, 2000)
    y[rest[:64], range(64)] = 1.0
    assert theory.doubling_dimension(frame(spark, y)) >= 5


def test_streams_of_two_batches_join(spark, tmp_path):
    # A stream's watermark begins at second 0, where rows count as late.
    for clicks, bought in (([(1, 1000), (2, 1010)], [(1, 1050), (2, 1010)]), ([(1, 5000)], [(1, 1100), (1, 1101), (2, 1060)])):
        for name, rows in (("click", clicks), ("buy", bought)):
            df = spark.createDataFrame(rows, "user long, s long").select("user", F.timestamp_seconds("s").alias(f"{name}_ts"))
            df.coalesce(1).write.mode("append").parquet(f"{tmp_path}/{name}")
    a, b = (serving.stream_of(spark, f"{tmp_path}/{n}", f"user long, {n}_ts timestamp") for n in ("click", "buy"))
    got = serving.drain(serving.join_streams(a, b, "user", "click_ts", "buy_ts", 100), f"{tmp_path}/run").select("user", F.unix_seconds("buy_ts").alias("s")).collect()
    assert sorted(map(tuple, got)) == [(1, 1050), (1, 1100), (2, 1060)]


def test_tombstones_from_a_stream(spark, tmp_path):
    p = points(60, 3)
    store = IndexStore(spark, str(tmp_path / "store"))
    store.write(frame(spark, p), "lcg_fixed", Params(K=8, M=8, L=10, C=20))
    for ids in ([3, 3, 4], [4, 5]):
        df = spark.createDataFrame([(i, n) for n, i in enumerate(ids)], "vec_id long, s long").select("vec_id", F.timestamp_seconds("s").alias("ts"))
        df.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        stream = serving.stream_of(spark, str(tmp_path / "in"), "vec_id long, ts timestamp")
        serving.tombstone_stream(stream, store, str(tmp_path / "cp")).awaitTermination()
    assert sorted(r.vec_id for r in spark.read.parquet(str(tmp_path / "store/tombstones")).collect()) == [3, 4, 5]
    asked = exact.as_queries(frame(spark, p).where("vec_id IN (3, 5)"))
    assert not {r.vec_id for r in store.search(asked, 3, 20).collect()} & {3, 4, 5}


def test_rebuild_keeps_what_comes_meanwhile(spark, tmp_path, monkeypatch):
    p = points(40, 3)
    store = IndexStore(spark, str(tmp_path))
    store.write(frame(spark, p[:30]), "lcg_fixed", Params(K=8, M=8, L=10, C=20))
    store.insert(frame(spark, p[30:32], 30))
    store.delete(spark.createDataFrame([(1,)], "vec_id long"))
    write = store.write

    def busy(*args):
        version = write(*args)
        store.insert(frame(spark, p[32:33], 32))
        store.delete(spark.createDataFrame([(2,)], "vec_id long"))
        return version

    monkeypatch.setattr(store, "write", busy)
    store.rebuild()
    assert [r.vec_id for r in store.live_delta().collect()] == [32]
    held = {r.vec_id for r in store.search(exact.as_queries(frame(spark, p[:1])), 40, 60).collect()}
    assert held == set(range(33)) - {1, 2}


def test_selected_edges_come_without_repairs(spark):
    x = np.concatenate([points(40, 2, 1), points(40, 2, 2) + 1000])
    index = stage(build.build_index(frame(spark, x), "lcg_adaptive", Params(K=5, M=6, L=10, C=20)), "islands")
    every, selected = build.edges_of(index), build.edges_of(index, repairs=False)
    n = index.agg(F.sum("n_repair")).first()[0]
    assert n > 0 and every.count() - selected.count() == n
    assert selected.join(every, ["src", "dst", "rank"]).count() == selected.count()


def test_a_confirmed_answer_is_exact_whatever_the_index_missed(spark):
    x = points(300, 8, 5)
    p = frame(spark, x)
    asked = exact.as_queries(p.where("vec_id % 20 = 0"))
    want = exact.exact_knn(p, asked, 5)
    key = lambda df: sorted(tuple(r) for r in df.select("q_id", "rank", "vec_id").collect())
    # A search that knows every third row alone, and nothing of some queries.
    poor = exact.exact_knn(p.where("vec_id % 3 = 0"), asked.where("q_id <> 40"), 5)
    assert key(poor) != key(want)
    assert key(query_plan.confirmed(query_plan.AnnQuery(5, 5), p, asked, poor)) == key(want)


def test_routes_that_make_visited_rows_alone_equal_those_over_the_graph(spark, monkeypatch):
    p = stage(frame(spark, np.concatenate([points(150, 4, 6), points(20, 4, 6)])), "route-points")
    rule, asked = ScaledShiftedBall(1.2, 0.05), exact.as_queries(p.where("vec_id % 9 = 0"))
    want = search.greedy_routes(p, build.full_graph(p, rule), asked, 0)
    key = lambda df: sorted((r.q_id, r.hop, r.vec_id, round(r.dist, 12)) for r in df.collect())
    want = key(want)
    monkeypatch.setattr(build, "full_graph", None)
    assert key(search.greedy_routes_full(p, rule, asked, 0)) == want


def test_a_cut_loses_the_far_region_and_adaptive_alpha_keeps_a_way(spark):
    hub = np.array([(0, 0), (0.1, 0), (0.11, 0.01), (0.12, -0.01), (0.13, 0), (0.105, 0.02), (0.115, -0.02), (-5, 0), (-5.5, 0.5), (-6, 0)], float)
    got = sorted((r.policy, r["rank"], r.dst, round(r.dist, 6)) for r in experiments.truncation(frame(spark, hub), 0, 9, 4).collect())
    assert got == [("adaptive", 1, 1, 0.1), ("adaptive", 2, 7, 5.0), ("nearest", 1, 1, 0.1), ("nearest", 2, 5, 0.106888), ("nearest", 3, 2, 0.110454), ("nearest", 4, 6, 0.116726)]


def test_the_truncation_query_reads_a_given_table(spark, small):
    ids = {r.vec_id for r in V.v_emb(spark, small).select("vec_id").collect()}
    rows = catalogue.QUERIES["w11_truncation"](spark, small).collect()
    assert {r.dst for r in rows} <= ids and sum(r.policy == "nearest" for r in rows) == 16


def test_range_scan_equals_the_pivot_join(spark):
    p = frame(spark, np.concatenate([points(150, 12, 8) * 0.05, points(20, 12, 8) * 0.05]))
    key = lambda df: sorted((r.l_id, r.r_id, round(r.dist, 12)) for r in df.collect())
    assert len(key(exact.range_scan(p, p, 0.2))) > 210 and key(exact.range_scan(p, p, 0.2)) == key(exact.range_join(p, p, 0.2))


def test_copies_of_parts_add_members_and_no_pairs(spark, small, tmp_path):
    part = spark.read.parquet(f"{small}/part.parquet")
    many = part.unionByName(part.withColumn("p_partkey", F.col("p_partkey") + 100_000)).unionByName(part.withColumn("p_partkey", F.col("p_partkey") + 200_000))
    many.write.parquet(f"{tmp_path}/part.parquet")
    one, three = (catalogue.QUERIES["tau_range_join"](spark, str(d)) for d in (small, tmp_path))
    n = lambda df, kind: df.where(F.col("kind") == kind).count()
    assert n(three, "member") == 3 * n(one, "member") == 3 * part.count()
    assert 0 < n(three, "near") <= n(one, "near") + 5


def test_boxes_find_the_same_neighbours_and_scan_few(spark):
    x = np.round(points(3000, 3, 9), 2)
    x[:900] = x[0]
    p = frame(spark, x)
    asked = exact.as_queries(p.where("vec_id % 50 = 0").select("vec_id", "embedding").union(frame(spark, [x[0] + 30, x[0] - 30], 9000)))
    key = lambda df: sorted((r.q_id, r["rank"], r.vec_id, r.dist) for r in df.collect())
    for k in (1, 10):
        assert key(exact.exact_knn_boxes(p, asked, k, box_rows=64)) == key(exact.exact_knn(p, asked, k))
    assert key(exact.exact_knn_boxes(p.limit(4), asked, 10)) == key(exact.exact_knn(p.limit(4), asked, 10))
    boxes = exact.Boxes(x, 40)
    own = boxes.of(x)
    assert ((x <= boxes.high[own]) & (x >= boxes.low[own])).all() and len(boxes.low) > 20
    assert sum(len(row) for row, _ in boxes.within(x[900:], np.full(2100, 0.05))) < 2100 * 8


def test_violations_by_blocks_equal_those_by_joins(spark):
    alpha, tau = 1.2, 0.1
    p = stage(frame(spark, np.concatenate([points(60, 2, 4), points(6, 2, 4)])), "checked-points")
    # A graph with gaps and edges too many, so that every statement is broken somewhere.
    g = stage(build.full_graph(p, ScaledShiftedBall(1.5, 0.2)).where("(src + dst) % 5 <> 0 AND src <> 7"), "checked-graph")
    asked = stage(exact.as_queries(p), "checked-queries")
    dist, pairs = theory.query_distances(p, asked), theory.pair_distances(p)
    key = lambda df, *c: sorted(tuple(r) for r in df.select(*c).collect())
    for got, want, c in (
        (theory.violations(p, g, asked, alpha, tau, "reducible"), theory.reducible_violations(g, dist, alpha, tau), ("q_id", "p")),
        (theory.violations(p, g, asked, alpha, tau, "shortcut"), theory.shortcut_violations(g, pairs, alpha, tau), ("p", "z")),
        (theory.close_kept(p, g, 1.01, 0.0), theory.packing_violations(g, pairs, 1.01, 0.0), ("src", "u", "v")),
    ):
        assert key(got, *c) == key(want, *c) and key(want, *c)


def test_statistics_without_all_pairs_equal_those_of_all_pairs(spark, monkeypatch):
    monkeypatch.setattr(exact, "BOX_ROWS", 64)
    monkeypatch.setattr(theory, "SPREAD_BLOCK", 100)
    for x in (points(700, 3, 1), np.abs(points(500, 4, 2)) ** 3, points(300, 20, 3), points(2, 2, 4), points(1, 2, 4)):
        p = stage(frame(spark, x), "spread-points")
        got = theory.spread(p, x.shape[1], theory.share_vectors(p))
        want = theory.aspect_ratio(p).first()
        assert got == pytest.approx((want.diameter, want.smallest, experiments.median_nearest(p)), rel=1e-12) if len(x) > 1 else got == (None, None, None)
    # Different vectors whose distance underflows don't hide the smallest positive distance.
    tiny = stage(frame(spark, np.array([[0.0, 0.0], [1e-200, 0.0], [3.0, 0.0], [3.0, 4.0]])), "spread-points")
    assert theory.spread(tiny, 2, None) == (5.0, 3.0, 1.5)


@pytest.mark.parametrize("metric", ["l2", "l1", "angular"])
def test_covers_by_blocks_equal_plain_covers(metric):
    space = exact.Metric(metric)
    for x in (points(900, 3, 5), points(500, 40, 6), np.repeat(points(60, 4, 7), 10, axis=0), np.arange(400.0)[:, None] / 8):
        x = space.prepare(x + 3)
        for radius in (0.01, 0.125, 0.5, 1.5):
            left, count = x, 0
            while len(left):
                left, count = left[space.rows(left, left[0]) > radius], count + 1
            assert theory.cover_size(x, radius, space) == count
            assert theory.cover_size(x, radius, space, count - 1) == count and theory.cover_size(x, radius, space, count) <= count


def test_statistics_leave_no_staged_rows(spark, small, monkeypatch):
    monkeypatch.setattr(V, "VIEWS", {v: V.VIEWS[v] for v in ("v_supp", "v_bench")})
    from annspark.plans import session

    before = list(session._staged.get(spark.sparkContext.applicationId, []))
    rows = {r.view: r for r in experiments.dataset_statistics(spark, small).collect()}
    ext = theory.aspect_ratio(V.v_supp(spark, small)).first()
    assert (rows["v_supp"].diameter, rows["v_supp"].smallest) == pytest.approx((ext.diameter, ext.smallest)) and rows["v_bench"].dim == 128
    assert session._staged[spark.sparkContext.applicationId][: len(before)] == before and not any("stat-points" in path for path in session._staged[spark.sparkContext.applicationId][len(before) :])


def test_invariants_of_insertion_are_broken_where_an_index_is(spark, small, monkeypatch):
    """Many shards, a wrong distance, a repeated edge and a loop."""
    monkeypatch.setattr(experiments, "SHARD_POINTS", 200)
    made = build.build_indexes

    def broken(*args, **kw):
        rows = made(*args, **kw)
        first = rows.where("level = 0 AND setting = 'vamana'").agg(F.min("src")).first()[0]
        at = (F.col("src") == first) & (F.col("setting") == "vamana") & (F.col("level") == 0)
        nbrs = F.when(at, F.concat(F.array(F.col("src")), F.array(F.col("nbrs")[1]), F.slice("nbrs", 2, 3))).otherwise(F.col("nbrs"))
        dists = F.when(at, F.concat(F.array(F.lit(0.0)), F.array(F.col("dists")[1]), F.array(F.col("dists")[1] + 1e-6), F.slice("dists", 3, 2))).otherwise(F.col("dists"))
        return rows.select(*[{"nbrs": nbrs.alias("nbrs"), "dists": dists.alias("dists")}.get(c, F.col(c)) for c in rows.columns])

    query = catalogue.QUERIES["insertion_invariants"]
    assert {r.violations for r in query(spark, small).collect()} == {0}
    monkeypatch.setattr(build, "build_indexes", broken)
    got = {(r.method, r.statement): r.violations for r in query(spark, small).collect() if r.violations}
    assert got == {("vamana", "loop"): 1, ("vamana", "repeated"): 2, ("vamana", "wrong_distance"): 1}
    shards = made(V.v_emb(spark, small), {"hnsw": ("hnsw", Params(hnsw_m=8, hnsw_ef=20))}, build.router_for(V.v_emb(spark, small), 200)).agg(F.count_distinct("shard")).first()[0]
    assert shards > 1


def test_swept_settings_equal_indexes_built_alone(spark, monkeypatch):
    p = stage(frame(spark, np.concatenate([points(300, 3, 1), points(40, 3, 2) + 30])), "swept-points")
    params = Params(K=12, M=8, L=10, C=40, tau=0.01)
    settings = {"fixed/1": ("lcg_fixed", replace(params, alpha=1.0)), "fixed/2": ("lcg_fixed", replace(params, tau=0.5)), "adaptive": ("lcg_adaptive", params)}
    columns = [c for c in build.build_indexes(p, settings).columns if c != "build_s"]
    key = lambda df: sorted(str(r) for r in df.select(*columns).collect())
    want = key(build.build_indexes(p, settings))
    # No task but those of the vertices searches the K-NN graph or selects from candidates.
    got = build.build_swept(p, settings)
    assert key(got) == want and got.agg(F.sum("n_repair")).first()[0] > 0
    # One K-NN graph, exact, also where a shard's own is refined from projections.
    monkeypatch.setattr("annspark.functions.graphs.EXACT_POINTS", 100)
    assert key(build.build_swept(p, settings)) == want
    with pytest.raises(ValueError):
        build.build_swept(p, {"a": ("lcg_fixed", params), "b": ("lcg_fixed", replace(params, L=20))})
    assert build.build_swept(frame(spark, points(1, 3)), settings).count() == 3


@pytest.mark.parametrize("method, backward", [("lcg_adaptive", None), ("lcg_fixed", None), ("nsg", "lazy")])
def test_one_shard_of_many_points_has_the_exact_graph(spark, method, backward):
    """Over 20,000 points, from which on a routed shard refines its K-NN graph."""
    x, params = points(20_200, 6, 3), Params(K=4, M=4, L=4, C=8, start=0, backward=backward)
    knn, dist = G.exact_knn_graph(x, 4)
    entry = G.find_entry(x, knn, 4, exact.Metric(), 1, 0)
    g = G.build_local(x, params, G.LOCAL[method][0], backward or "lazy", prepared=(entry, G.local_candidates(x, knn, dist, entry, params, exact.Metric())))
    got = build.build_index(frame(spark, x), method, params).select("src", "nbrs", "is_entry").orderBy("src").toArrow().to_pydict()
    assert got["nbrs"] == g.neighbors and got["is_entry"].index(True) == entry


@pytest.mark.parametrize("method", ["nsg", "shifted_local", "lcg_adaptive_eager"])
def test_vertices_built_in_many_tasks_equal_a_shard_built_in_one(spark, method):
    p = stage(frame(spark, np.concatenate([points(300, 3, 1), points(40, 3, 2) + 30])), "parted-points")
    columns = ["src", "nbrs", "dists", "is_entry", "n_repair", "steps", "pairs", "selections"]
    key = lambda df: sorted(str(r) for r in df.select(*columns).collect())
    for way in (None, "none", "lazy"):
        params = Params(K=12, M=8, L=10, C=40, tau=0.01, backward=way)
        assert key(build.build_index(p, method, params)) == key(build.build_indexes(p, {method: (method, params)}))


def test_checks_of_lists_equal_those_of_edges(spark):
    """Checks and routes of a graph with a dense middle: as lists it is neither collected nor broadcast, and full rows are those of the plain filter."""
    alpha, tau, rule = 1.2, 0.05, ScaledShiftedBall(1.2, 0.05)
    x = np.concatenate([points(250, 3, 4) * 0.06, points(150, 3, 5), np.repeat(points(3, 3, 6), 20, axis=0)])
    p = stage(frame(spark, x), "listed-points")
    g, rows = stage(build.full_graph(p, rule), "listed-graph"), stage(build.full_graph(p, rule, lists=True), "listed-rows")
    key = lambda df, *c: sorted(tuple(r) for r in df.select(*c).collect())
    edge = ("src", "dst", "dist", "rank")
    assert key(g, *edge) == key(build.edges_of(rows.selectExpr("0 AS shard", "*", "0 AS level")), *edge)
    full, plain = G.FullRows(x, rule), G.FullRows(x, rule)
    plain.few = False
    for a, b, c in zip(full.rows(np.arange(0, len(x), 7)), plain.rows(np.arange(0, len(x), 7)), full.rows(np.arange(0, len(x), 7), 5)):
        assert (a[0].tolist(), a[1].tolist(), a[0][:5].tolist()) == (b[0].tolist(), b[1].tolist(), c[0].tolist())
    assert "balls" in vars(full) and "balls" not in vars(plain)
    asked = stage(exact.as_queries(p).withColumn("qvec", F.transform("qvec", lambda v: v + 0.01)), "listed-queries")
    route = ("q_id", "hop", "vec_id", "dist")
    assert key(search.greedy_routes(p, rows, asked, 3), *route) == key(search.greedy_routes(p, g, asked, 3), *route)
    some = rows.where("src % 9 <> 4").select("src", F.slice("nbrs", 2, 9).alias("nbrs"), F.slice("dists", 2, 9).alias("dists"))
    few = g.where("src % 9 <> 4 AND rank BETWEEN 2 AND 10")
    dist, pairs = theory.query_distances(p, asked), theory.pair_distances(p)
    for got, want, c in (
        (theory.violations(p, some, asked, alpha, tau, "reducible"), theory.reducible_violations(few, dist, alpha, tau), ("q_id", "p")),
        (theory.violations(p, some, exact.as_queries(p), alpha, tau, "shortcut"), theory.shortcut_violations(few, pairs, alpha, tau), ("p", "z")),
        (theory.close_kept(p, rows, 1.5, 0.01), theory.packing_violations(g, pairs, 1.5, 0.01), ("src", "u", "v")),
    ):
        assert key(got, *c) == key(want, *c) and key(want, *c)
