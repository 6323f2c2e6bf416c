"""Accuracy and cost measures as joins and aggregates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def recall_at_k(found: DataFrame, truth: DataFrame, k: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(by.., q_id, recall): the share of a query's true k that is among the first k found; queries without hits count as 0.

    ``found`` has q_id, vec_id and the ``by`` columns; ``truth`` has q_id, rank, vec_id.
    """
    true = truth.where(F.col("rank") <= k).select("q_id", "vec_id")
    best = W.partitionBy(*by, "q_id").orderBy("dist", "vec_id")
    got = found.withColumn("_r", F.row_number().over(best)).where(F.col("_r") <= k)
    hits = got.join(true, ["q_id", "vec_id"]).groupBy(*by, "q_id").agg(F.count("*").alias("hits"))
    asked = true.groupBy("q_id").agg(F.count("*").alias("n"))
    if by:
        # Every setting that occurs meets every query: a table of settings, not of rows.
        asked = asked.join(F.broadcast(found.select(*by).distinct()), F.lit(True))
    return asked.join(hits, [*by, "q_id"], "left").select(*by, "q_id", (F.coalesce("hits", F.lit(0)) / F.col("n")).alias("recall"))


def curve(found: DataFrame, truth: DataFrame, k: int, by: tuple[str, ...] = ("width",)) -> DataFrame:
    """(by.., recall, ndc, hops, edges_scanned): means over queries for each setting."""
    costs = found.groupBy(*by, "q_id").agg(*[F.max(c).alias(c) for c in ("ndc", "hops", "edges_scanned")])
    each = recall_at_k(found, truth, k, by).join(costs, [*by, "q_id"], "left")
    return each.groupBy(*by).agg(*[F.avg(c).alias(c) for c in ("recall", "ndc", "hops", "edges_scanned")])


def cost_at_recall(curves: DataFrame, target: float, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """(by.., ndc, hops): the least cost at ``target`` recall, by linear interpolation along each curve."""
    along = W.partitionBy(*by).orderBy("ndc", "recall")
    high = F.max("recall").over(along.rowsBetween(W.unboundedPreceding, 0))
    pts = curves.withColumn("r", high)
    prev = {c: F.lag(c).over(along) for c in ("r", "ndc", "hops")}
    pts = pts.select(*by, "r", "ndc", "hops", *[v.alias(f"p_{c}") for c, v in prev.items()])
    share = F.when(F.col("p_r").isNull() | (F.col("p_r") >= F.col("r")), 1.0).otherwise((F.lit(target) - F.col("p_r")) / (F.col("r") - F.col("p_r")))
    at = lambda c: F.when(F.col("p_r").isNull(), F.col(c)).otherwise(F.col(f"p_{c}") + share * (F.col(c) - F.col(f"p_{c}")))
    first = pts.where((F.col("r") >= target) & (F.coalesce("p_r", F.lit(-1.0)) < target))
    return first.groupBy(*by).agg(F.min(at("ndc")).alias("ndc"), F.min(at("hops")).alias("hops"))


def speedup_at_recall(curves: DataFrame, target: float, ours: str, baselines: tuple[str, ...]) -> DataFrame:
    """(measure, ours, best_baseline, value, speedup): the best baseline's cost over ours, at equal recall.

    Where no baseline reaches the target, its columns and the speedup are null.
    """
    at = cost_at_recall(curves, target)
    long = at.unpivot(["method"], ["ndc", "hops"], "measure", "value")
    mine = long.where(F.col("method") == ours).select("measure", F.col("value").alias("ours"))
    best = long.where(F.col("method").isin(*baselines)).groupBy("measure").agg(F.min("value").alias("value"), F.min_by("method", "value").alias("best_baseline"))
    return mine.join(best, "measure", "left").select("measure", "ours", "best_baseline", "value", (F.col("value") / F.col("ours")).alias("speedup"))


def degree_stats(edges: DataFrame, n: int | None = None) -> DataFrame:
    """(vertices, edges, mean_degree, max_degree, p50, p90): out-degrees; ``n`` counts vertices without edges too."""
    deg = edges.groupBy("src").agg(F.count("*").alias("degree"))
    whole = F.lit(n) if n is not None else F.count("*")
    return deg.agg(
        whole.cast("long").alias("vertices"), F.sum("degree").alias("edges"), (F.sum("degree") / whole).alias("mean_degree"), F.max("degree").alias("max_degree"),
        F.percentile("degree", 0.5).alias("p50"), F.percentile("degree", 0.9).alias("p90"),
    )


def degree_histogram(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("vertices"))


def long_edge_share(edges: DataFrame, longer_than: float) -> DataFrame:
    return edges.agg(F.avg(F.when(F.col("dist") > longer_than, 1.0).otherwise(0.0)).alias("long_share"), F.percentile_approx("dist", [0.1, 0.5, 0.9], 10_000).alias("quantiles"))


def index_stats(index: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by.., vertices, edges, index_mb, vector_mb, build_s): adjacency at 4 bytes a local id, vectors at 4 bytes a component, CPU seconds of all shards.

    A shard's rows all hold its seconds, or, where vertices were built apart, each its own.
    """
    own = F.when(F.min("build_s") == F.max("build_s"), F.max("build_s")).otherwise(F.sum("build_s"))
    build = index.where("level = 0").groupBy(*by, "shard").agg(own.alias("s")).groupBy(*by).agg(F.sum("s").alias("build_s"))
    sizes = index.groupBy(*by).agg(
        F.count_if(F.col("level") == 0).alias("vertices"), F.sum(F.size("nbrs")).alias("edges"),
        (F.sum(F.size("nbrs")) * 4 / 1e6).alias("index_mb"), (F.sum(F.when(F.col("level") == 0, F.size("vec"))) * 4 / 1e6).alias("vector_mb"),
    )
    return sizes.join(build, list(by)) if by else sizes.join(build, F.lit(True))


def selection_work(index: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by.., pairs, mean_steps, mean_alpha, mean_distinct, selections, repair_edges): what neighbour selection did, over all shards."""
    base = index.where("level = 0")
    calls = base.groupBy(*by, "shard").agg(F.max("selections").alias("s")).groupBy(*by).agg(F.sum("s").alias("selections"))
    work = base.groupBy(*by).agg(
        F.sum("pairs").alias("pairs"), F.avg("steps").alias("mean_steps"), F.avg("alpha_used").alias("mean_alpha"), F.avg("distinct_kept").alias("mean_distinct"), F.sum("n_repair").alias("repair_edges"),
    )
    both = work.join(calls, list(by)) if by else work.join(calls, F.lit(True))
    return both.select(*by, "pairs", "mean_steps", "mean_alpha", "mean_distinct", "selections", "repair_edges")


def approx_ratio(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(q_id, ratio): the nearest found over the true nearest; 1 where both are zero."""
    best = found.groupBy("q_id").agg(F.min("dist").alias("got"))
    near = truth.where("rank = 1").select("q_id", F.col("dist").alias("true"))
    return near.join(best, "q_id", "left").select("q_id", F.when(F.col("got") == F.col("true"), 1.0).otherwise(F.col("got") / F.col("true")).alias("ratio"))


def tau_coverage(truth: DataFrame, taus: list[float]) -> DataFrame:
    """(tau, share): queries whose nearest neighbour is within tau."""
    near = truth.where("rank = 1").select("dist", F.explode(F.array(*map(F.lit, taus))).alias("tau"))
    return near.groupBy("tau").agg(F.avg(F.when(F.col("dist") <= F.col("tau"), 1.0).otherwise(0.0)).alias("share"))


def ring_histogram(pairs: DataFrame, diameter: float) -> DataFrame:
    """(src, ring, n): other points by rings whose outer radius halves; ``pairs`` has src, dst, dist > 0.

    Ring i holds distances in (diameter / 2**(i+1), diameter / 2**i].
    """
    ring = F.floor(F.log2(F.lit(diameter) / F.col("dist")))
    # A logarithm may round across a power of two; comparisons settle it.
    ring = F.when(F.col("dist") <= F.lit(diameter) / F.pow(F.lit(2.0), ring + 1), ring + 1).when(F.col("dist") > F.lit(diameter) / F.pow(F.lit(2.0), ring), ring - 1).otherwise(ring)
    return pairs.select("src", ring.cast("int").alias("ring")).groupBy("src", "ring").agg(F.count("*").alias("n"))


def graph_recall(graph: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(recall): the share of exact K-NN edges that an approximate K-NN graph has."""
    true = truth.where(F.col("rank") <= k).select("src", "dst")
    hit = true.join(graph.select("src", "dst").distinct(), ["src", "dst"], "left_semi")
    return true.agg(F.count("*").alias("n")).join(hit.agg(F.count("*").alias("hits")), F.lit(True)).select((F.col("hits") / F.col("n")).alias("recall"))
