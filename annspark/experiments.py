"""The experiment workloads on the given tables.

Every function takes (spark, sf_dir) and returns a table of measures. Queries
are the rows whose id is divisible by EVERY; the rest is the base. Costs are
distance computations and hops, which don't depend on the machine; times are
ours alone. Recall is at K unless said otherwise. Indexes are built once an
application for each view, method and setting, and shared by the workloads.
"""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.functions import graphs as G
from annspark.functions.rules import ScaledBall, ScaledShiftedBall, ShiftedBall, UnitBall
from annspark.operators import build, exact, measures, search, selecting, theory, tune
from annspark.plans.session import releases, scratch, stage
from annspark.sources import vectors as V

EVERY = 20
PRACTICAL = ("lcg_adaptive", "lcg_fixed", "nsg", "shifted_local", "hnsw", "vamana")
BASELINES = ("nsg", "shifted_local", "hnsw", "vamana")
TRANSPLANT = ("hnsw", "hnsw_plus", "vamana", "vamana_plus", "lcg_adaptive")
#: Settings by view: published degree caps, and alpha and tau for these data.
PARAMS = {
    "v_emb": replace(G.PRESETS["degree_50"], alpha=1.05, tau=0.001),
    "v_event": replace(G.PRESETS["degree_50"], alpha=1.2, tau=0.005),
    "v_part": replace(G.PRESETS["degree_50"], alpha=1.2, tau=0.005),
    "v_doc": replace(G.PRESETS["degree_70"], alpha=1.05, tau=0.01),
    "v_line": replace(G.PRESETS["degree_50"], K=60, C=200, alpha=1.2, tau=0.005),
}
K, WIDTHS = 100, [100, 120, 160, 240, 400]
SMALL_K, SMALL_WIDTHS = 10, [10, 15, 20, 30, 40, 80, 160]
#: Points that one shard of an experiment holds; larger views get more shards.
SHARD_POINTS = 12_500
PROBES = 2
#: Views whose statistics are taken at the same time.
VIEWS_TOGETHER = 3
#: What an application has staged already, by its key.
_held: dict[tuple, DataFrame] = {}


def _application(spark: SparkSession) -> tuple[str, int]:
    return spark.sparkContext.applicationId, releases(spark)


def once(spark: SparkSession, key: tuple, make) -> DataFrame:
    """A staged table that the workloads of one application share."""
    key = (*_application(spark), *key)
    if key not in _held:
        _held[key] = stage(make(), "-".join(map(str, key[3:5])))
    return _held[key]


def split(spark: SparkSession, sf_dir: str, view: str, part: int = 1) -> tuple[DataFrame, DataFrame]:
    """(base, queries) of a view, or of one in ``part`` of its rows: copies collapsed, both written once."""
    points = once(spark, (sf_dir, "points", view), lambda: V.collapse_duplicates(V.VIEWS[view](spark, sf_dir)).select("vec_id", "embedding"))
    base, asked = V.hold_out(points, EVERY)
    smaller = base.where(F.pmod(F.xxhash64("vec_id"), F.lit(part)) == 0)  # the sizes of the scalability workload
    return once(spark, (sf_dir, "base", view, part), lambda: smaller), once(spark, (sf_dir, "queries", view), lambda: exact.as_queries(asked))


def truth_of(spark: SparkSession, sf_dir: str, view: str, k: int = K, part: int = 1) -> DataFrame:
    base, asked = split(spark, sf_dir, view, part)
    return once(spark, (sf_dir, "truth", view, k, part), lambda: exact.exact_knn(base, asked, k))


def indexes(spark: SparkSession, sf_dir: str, view: str, methods: tuple[str, ...], params: G.Params | None = None, part: int = 1) -> tuple[DataFrame, build.Router | None]:
    """(index rows of all ``methods``, router); methods not built yet are built side by side."""
    base, _ = split(spark, sf_dir, view, part)
    params = params or PARAMS[view]
    app = _application(spark)
    router_key = (*app, sf_dir, "router", view, part)
    if router_key not in _held:
        _held[router_key] = build.router_for(base, SHARD_POINTS)
    key = lambda m: (sf_dir, "index", view, m, params, part)
    missing = [m for m in methods if (*app, *key(m)) not in _held]
    if missing:
        rows = stage(build.build_indexes(base, {m: (m, params) for m in missing}, _held[router_key]), f"index-{view}")
        for m in missing:
            _held[(*app, *key(m))] = rows.where(F.col("setting") == m)
    out = None
    for m in methods:
        out = _held[(*app, *key(m))] if out is None else out.unionByName(_held[(*app, *key(m))])
    return out, _held[router_key]


def curves(spark: SparkSession, sf_dir: str, view: str, methods: tuple[str, ...] = PRACTICAL, k: int = K, widths: list[int] = WIDTHS, params: G.Params | None = None, part: int = 1) -> DataFrame:
    """(view, method, width, recall, ndc, hops, edges_scanned): recall against cost as the queue widens."""

    def make() -> DataFrame:
        _, asked = split(spark, sf_dir, view, part)
        index, router = indexes(spark, sf_dir, view, methods, params, part)
        found = search.search_indexes(index, list(methods), asked, k, widths, router, PROBES)
        got = measures.curve(found, truth_of(spark, sf_dir, view, k, part), k, ("setting", "width"))
        return got.select(F.lit(view).alias("view"), F.col("setting").alias("method"), "width", "recall", "ndc", "hops", "edges_scanned")

    return once(spark, (sf_dir, "curves", view, methods, k, tuple(widths), params, part), make)


def cost_at_levels(spark: SparkSession, sf_dir: str, view: str, levels: tuple[float, ...] = (0.9, 0.95, 0.99)) -> DataFrame:
    """(view, target, measure, ours, best_baseline, value, speedup) at equal recall."""
    c = curves(spark, sf_dir, view)
    out = None
    for level in levels:
        part = measures.speedup_at_recall(c, level, "lcg_adaptive", BASELINES).select(F.lit(view).alias("view"), F.lit(level).alias("target"), "*")
        out = part if out is None else out.unionByName(part)
    return out


def scalability(spark: SparkSession, sf_dir: str, view: str = "v_event", target: float = 0.98) -> DataFrame:
    """(view, n, method, recall_best, ndc, hops, hop_reduction): cost at ``target`` recall at a quarter, half and all of a view.

    hop_reduction is one less the method's hops over the best baseline's at that size.
    """
    out = None
    for part in (4, 2, 1):
        c = curves(spark, sf_dir, view, part=part)
        n = split(spark, sf_dir, view, part)[0].count()
        at = c.groupBy("method").agg(F.max("recall").alias("recall_best")).join(measures.cost_at_recall(c, target), "method", "left")
        best = F.min(F.when(F.col("method").isin(*BASELINES), F.col("hops")))
        one = at.join(at.agg(best.alias("best")), F.lit(True)).select(F.lit(view).alias("view"), F.lit(n).cast("long").alias("n"), "method", "recall_best", "ndc", "hops", (1 - F.col("hops") / F.col("best")).alias("hop_reduction"))
        out = one if out is None else out.unionByName(one)
    return out


def median_nearest(base: DataFrame) -> float:
    """The median over every row of the distance to its nearest other."""
    return exact.exact_knn(base, exact.as_queries(base), 1, skip_self=True).agg(F.median("dist")).first()[0]


def _sweep(spark: SparkSession, sf_dir: str, view: str, settings: list[tuple[str, float, float]]) -> DataFrame:
    base, asked = split(spark, sf_dir, view)
    return tune.sweep(base, asked, settings, PARAMS[view], K, WIDTHS, shard_points=SHARD_POINTS).select(F.lit(view).alias("view"), "*")


def tau_effect(spark: SparkSession, sf_dir: str, view: str = "v_emb") -> DataFrame:
    """Fixed variant as tau grows from 0 by multiples of the median nearest distance."""
    step = median_nearest(split(spark, sf_dir, view)[0])
    return _sweep(spark, sf_dir, view, [("fixed", PARAMS[view].alpha, step * m) for m in (0.0, 0.01, 0.1, 0.5, 2.0)])


def alpha_effect(spark: SparkSession, sf_dir: str, view: str = "v_emb") -> DataFrame:
    """Fixed variant at growing alphas, and the adaptive one."""
    p = PARAMS[view]
    return _sweep(spark, sf_dir, view, [("fixed", a, p.tau) for a in (1.0, 1.05, 1.2, 1.4)] + [("adaptive", p.alpha, p.tau)])


def tau_search(spark: SparkSession, sf_dir: str, view: str = "v_emb") -> DataFrame:
    """The grid search on tuning queries (ids that leave 1) kept away from base and test queries."""
    base, _ = split(spark, sf_dir, view)
    tuning = F.pmod(F.col("vec_id"), F.lit(EVERY)) == 1
    return tune.tune_tau(base.where(~tuning), exact.as_queries(base.where(tuning)), PARAMS[view], SMALL_K, SMALL_WIDTHS)


def alpha_search(spark: SparkSession, sf_dir: str, view: str = "v_emb") -> DataFrame:
    """Three values of alpha on the tuning queries, by the fixed variant's cost."""
    base, _ = split(spark, sf_dir, view)
    tuning = F.pmod(F.col("vec_id"), F.lit(EVERY)) == 1
    p = PARAMS[view]
    return tune.tune_alpha(base.where(~tuning), exact.as_queries(base.where(tuning)), p, SMALL_K, SMALL_WIDTHS, (1.0, p.alpha, 1.1))


def build_cost(spark: SparkSession, sf_dir: str, view: str = "v_emb", methods: tuple[str, ...] = (*PRACTICAL, "lcg_adaptive_eager", "hnsw_plus", "vamana_plus")) -> DataFrame:
    """(view, method, build_s, vertices, edges, index_mb, vector_mb, mean_degree, max_degree, pairs, ..): build_s is CPU seconds over all shards."""
    index, _ = indexes(spark, sf_dir, view, methods)
    degree = index.where("level = 0").groupBy("setting").agg(F.avg(F.size("nbrs")).alias("mean_degree"), F.max(F.size("nbrs")).alias("max_degree"))
    work = measures.selection_work(index, ("setting",)).select("setting", "pairs", "mean_steps", "mean_alpha", "selections", "repair_edges")
    rows = measures.index_stats(index, ("setting",)).join(degree, "setting").join(work, "setting")
    return rows.select(F.lit(view).alias("view"), F.col("setting").alias("method"), *[c for c in rows.columns if c != "setting"])


def transplant(spark: SparkSession, sf_dir: str, view: str = "v_doc") -> DataFrame:
    """The two insertion baselines with their own rule and with the scaled-shifted one."""
    return curves(spark, sf_dir, view, TRANSPLANT)


def throughput(spark: SparkSession, sf_dir: str, view: str = "v_emb") -> DataFrame:
    """(view, method, width, queries, seconds, queries_per_second): search of all queries, timed around the job."""
    _, asked = split(spark, sf_dir, view)
    n, rows = asked.count(), []
    for method in PRACTICAL:
        index, router = indexes(spark, sf_dir, view, (method,))
        for width in (WIDTHS[0], WIDTHS[-1]):
            began = time.time()
            search.search_indexes(index, [method], asked, K, [width], router, PROBES).write.format("noop").mode("overwrite").save()
            took = time.time() - began
            rows.append((view, method, width, n, took, n / took))
    return spark.createDataFrame(rows, "view string, method string, width int, queries long, seconds double, queries_per_second double")


def truncation(points: DataFrame, hub: int, top: int, m: int) -> DataFrame:
    """(policy, rank, dst, dist): a hub's edges when its ``top`` nearest candidates are cut to the ``m`` nearest, and when alpha adapts.

    A tight bunch on one side takes all places by distance; the adaptive policy keeps ways to far regions.
    """
    asked = exact.as_queries(points.where(F.col("vec_id") == hub))
    near = stage(exact.exact_knn(points, asked, top, skip_self=True).select(F.col("q_id").alias("src"), F.col("vec_id").alias("dst"), "dist", "rank"), "hub-candidates")
    cut = near.where(F.col("rank") <= m).select(F.lit("nearest").alias("policy"), "rank", "dst", "dist")
    kept = selecting.adaptive(points, top, G.Params(M=m), near=near).select(F.posexplode(F.split("kept", ",")).alias("at", "id"))
    kept = kept.select((F.col("at") + 1).alias("rank"), F.col("id").cast("long").alias("dst")).join(near.select("dst", "dist"), "dst")
    return cut.unionByName(kept.select(F.lit("adaptive").alias("policy"), "rank", "dst", "dist"))


def reuse(spark: SparkSession, sf_dir: str, view: str = "v_emb") -> DataFrame:
    """Distances between candidates with and without reuse: sums, their ratio, and mean steps of alpha."""
    base, _ = split(spark, sf_dir, view)
    p = replace(PARAMS[view], C=200)
    work = selecting.work_ablation(base, min(p.C, base.count() - 1), p)
    return work.agg(
        F.sum("pairs_reused").alias("pairs_reused"), F.sum("pairs_plain").alias("pairs_plain"), (F.sum("pairs_plain") / F.sum("pairs_reused")).alias("saving"),
        F.avg("steps").alias("mean_steps"), F.avg("distinct").alias("mean_distinct"),
    )


def backward(spark: SparkSession, sf_dir: str, view: str = "v_emb") -> DataFrame:
    """Lazy against eager backward insertion: selections made, edges and time."""
    return build_cost(spark, sf_dir, view, ("lcg_adaptive", "lcg_adaptive_eager")).select("method", "selections", "edges", "build_s")


def rules_compared(spark: SparkSession, sf_dir: str, view: str = "v_supp") -> DataFrame:
    """(rule, regime, queries, exact, mean_hops, max_ratio, mean_degree) of full graphs: queries in the data, within tau, and beyond."""
    p = stage(V.collapse_duplicates(V.VIEWS[view](spark, sf_dir)).select("vec_id", "embedding"), "rule-points")
    tau = 0.05
    shift = lambda by: F.transform("embedding", lambda v, i: F.when(i == F.col("vec_id") % F.size("embedding"), v + by).otherwise(v))
    asked = None
    for regime, by in (("in_data", F.lit(0.0)), ("within_tau", F.lit(tau) * (F.col("vec_id") % 7) / 8), ("beyond", F.lit(tau) * 8)):
        part = p.select((F.col("vec_id") * 4 + {"in_data": 0, "within_tau": 1, "beyond": 2}[regime]).alias("q_id"), shift(by).alias("qvec"), F.lit(regime).alias("regime"))
        asked = part if asked is None else asked.unionByName(part)
    asked = stage(asked, "rule-queries")
    truth = stage(exact.exact_knn(p, asked, 1).select("q_id", F.col("dist").alias("true")), "rule-truth")
    entry = p.agg(F.min("vec_id")).first()[0]
    out = None
    for rule in (UnitBall(), ShiftedBall(tau), ScaledBall(1.2), ScaledShiftedBall(1.2, tau)):
        g = stage(build.full_graph(p, rule), "rule-graph")
        last = search.greedy_routes(p, g, asked, entry).groupBy("q_id").agg((F.max("hop") + 1).alias("hops"), F.min("dist").alias("got"))
        each = last.join(truth, "q_id").join(asked.select("q_id", "regime"), "q_id")
        near = F.col("got") <= F.col("true") + theory.EPS
        part = each.groupBy("regime").agg(
            F.count("*").alias("queries"), F.avg(near.cast("double")).alias("exact"), F.avg("hops").alias("mean_hops"), F.max(F.when(near, 1.0).otherwise(F.col("got") / F.col("true"))).alias("max_ratio")
        )
        degree = measures.degree_stats(g, p.count()).select("mean_degree")
        part = part.join(degree, F.lit(True)).select(F.lit(rule.name).alias("rule"), "*")
        out = part if out is None else out.unionByName(part)
    return out


def dataset_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(view, n, dim, diameter, smallest, ratio, median_nearest, doubling_dim) of every view, a few views at a time."""

    def one(view: str) -> tuple:
        p = stage(V.collapse_duplicates(V.VIEWS[view](spark, sf_dir)).select("vec_id", "embedding"), "stat-points")
        dim, shared = len(p.first().embedding), theory.share_vectors(p)
        high, low, median = theory.spread(p, dim, shared)
        row = (view, len(shared.value), dim, high, low, high / low if low else None, median, theory.doubling_dimension(p, shared=shared))
        shared.destroy()
        return row

    # Most of a small view's time is the start of its jobs.
    with scratch(spark), ThreadPoolExecutor(VIEWS_TOGETHER) as pool:
        rows = list(pool.map(one, V.VIEWS))
    return spark.createDataFrame(rows, "view string, n long, dim int, diameter double, smallest double, ratio double, median_nearest double, doubling_dim double")


def candidate_quality(spark: SparkSession, sf_dir: str, view: str = "v_emb") -> DataFrame:
    """(source, recall): share of a point's 10 nearest among its candidates, found on a K-NN graph or among earlier inserts."""
    import pyarrow as pa

    from annspark.functions.metric import Metric
    from annspark.operators.exact import to_matrix

    base, _ = split(spark, sf_dir, view)
    p = PARAMS[view]

    def run(rows: pa.Table) -> pa.Table:
        import numpy as np

        x = to_matrix(rows.sort_by("vec_id").column("embedding"))
        near, _ = Metric().nearest(x, x, np.arange(len(x)), min(10, len(x) - 1), skip=np.arange(len(x)))
        _, pools = G.prepare_local(x, G.replace_knn(p), Metric())
        local = np.mean([np.isin(near[v], ids).mean() for v, (ids, _) in enumerate(pools)])
        place = np.argsort(np.argsort(G.mix(np.arange(len(x)), p.seed), kind="stable"))
        earlier = np.mean([(place[near[v]] < place[v]).mean() for v in range(len(x))])
        return pa.table({"source": ["knn_graph_search", "earlier_inserts"], "recall": [float(local), float(earlier)]})

    return base.withColumn("g", F.lit(0)).groupBy("g").applyInArrow(run, "source string, recall double")


def self_findability(spark: SparkSession, sf_dir: str, view: str = "v_emb") -> DataFrame:
    """(method, share): base points that a search for themselves returns first."""
    base, _ = split(spark, sf_dir, view)
    index, router = indexes(spark, sf_dir, view, ("lcg_adaptive", "nsg"))
    found = search.search_indexes(index, ["lcg_adaptive", "nsg"], exact.as_queries(base), 1, [20], router, PROBES)
    return found.groupBy(F.col("setting").alias("method")).agg(F.avg((F.col("q_id") == F.col("vec_id")).cast("double")).alias("share"))


def text_retrieval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items against document classes: recall and costs of the adaptive graph."""
    base, _ = split(spark, sf_dir, "v_doc")
    asked = stage(exact.as_queries(V.v_bench(spark, sf_dir)), "text-queries")
    index, router = indexes(spark, sf_dir, "v_doc", ("lcg_adaptive",))
    return measures.curve(search.search_index(index.drop("setting"), asked, K, WIDTHS, router, PROBES), exact.exact_knn(base, asked, K), K)


def _each(name: str, work, views: tuple[str, ...]) -> dict:
    return {f"{name}_{view[2:]}": lambda s, d, view=view: work(s, d, view) for view in views}


FIVE, FOUR, THREE = ("v_emb", "v_doc", "v_event", "v_part", "v_line"), ("v_emb", "v_doc", "v_event", "v_part"), ("v_emb", "v_doc", "v_event")
WORKLOADS = {
    **_each("w01_curves", curves, FIVE), **_each("w03_speedups", cost_at_levels, FIVE), **_each("w04_scalability", scalability, ("v_event", "v_doc")),
    **_each("w05_tau", tau_effect, FOUR), **_each("w06_alpha", alpha_effect, FOUR), "w06_alpha_search": alpha_search, **_each("w07_build_cost", build_cost, FOUR), **_each("w08_transplant", transplant, FOUR),
    "w09_reuse": reuse, "w10_backward": backward, "w12_tau_search": tau_search, "w13_rules": rules_compared, "w15_text_retrieval": text_retrieval, "w16_statistics": dataset_statistics,
    **_each("w17_throughput", throughput, THREE), "candidate_quality": candidate_quality, "self_findability": self_findability,
}
