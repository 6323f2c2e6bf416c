"""Parameter search: tau by a grid that is then refined, and alpha of the fixed variant.

Settings are indexes built side by side, each shard of each in a task of its own; those over one shard share what
neither alpha nor tau touches.
Tuning queries are disjoint from test queries.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from annspark.functions import graphs as G
from annspark.operators.build import SHARD_POINTS, build_indexes, build_swept, router_for
from annspark.operators.exact import exact_knn
from annspark.operators.measures import cost_at_recall, curve
from annspark.operators.search import search_indexes
from annspark.plans.session import stage

#: The starting grid: zero against powers of ten.
TAU_GRID = (0.0, 10.0, 1.0, 0.1, 0.01, 0.001)


def sweep(points: DataFrame, queries: DataFrame, settings: list[tuple[str, float, float]], params: G.Params, k: int, widths: list[int], metric: str = "l2", shard_points: int = SHARD_POINTS, probes: int = 2) -> DataFrame:
    """(policy, alpha, tau, width, recall, ndc, hops, mean_degree) of each (policy, alpha, tau) at each width."""
    spark = points.sparkSession
    named = {f"{policy}/{alpha!r}/{tau!r}": (f"lcg_{policy}", replace(params, alpha=alpha, tau=tau)) for policy, alpha, tau in settings}
    router = router_for(points, shard_points, metric)
    truth = stage(exact_knn(points, queries, k, metric), "sweep-truth")
    index = stage(build_swept(points, named, metric) if router is None else build_indexes(points, named, router, metric), "sweep-index")
    found = search_indexes(index, list(named), queries, k, widths, router, probes, metric)
    degree = index.groupBy("setting").agg(F.avg(F.size("nbrs")).alias("mean_degree"))
    about = spark.createDataFrame([(n, *s) for n, s in zip(named, settings)], "setting string, policy string, alpha double, tau double")
    rows = curve(found, truth, k, ("setting", "width")).join(F.broadcast(about), "setting").join(F.broadcast(degree), "setting")
    return rows.select("policy", "alpha", "tau", "width", "recall", "ndc", "hops", "mean_degree")


def _best(curves: DataFrame, by: str, target: float) -> tuple[float, DataFrame]:
    """(best value, costs at ``target`` recall by value); settings that miss it come last."""
    costs = stage(curves.select(F.col(by)).distinct().join(cost_at_recall(curves, target, (by,)), by, "left").orderBy(F.asc_nulls_last("ndc"), by), "tuned")
    return costs.orderBy(F.asc_nulls_last("ndc"), by).first()[by], costs


def tune_tau(points: DataFrame, queries: DataFrame, params: G.Params, k: int, widths: list[int], target: float = 0.9, grid=TAU_GRID, refine: int = 2) -> DataFrame:
    """(tau, ndc, hops, place): the grid, then ``refine`` rounds of halves and doubles around the best so far."""
    done = list(dict.fromkeys(grid))
    curves = stage(sweep(points, queries, [("fixed", params.alpha, t) for t in done], params, k, widths), "tau-curves")
    best, costs = _best(curves, "tau", target)
    for _ in range(refine):
        new = [t for t in (best / 2, best * 2) if best > 0 and t not in done]
        if not new:
            break
        done += new
        curves = stage(curves.unionByName(sweep(points, queries, [("fixed", params.alpha, t) for t in new], params, k, widths)), "tau-curves")
        best, costs = _best(curves, "tau", target)
    from pyspark.sql import Window as W

    return costs.withColumn("place", F.rank().over(W.orderBy(F.asc_nulls_last("ndc"), "tau")))  # one row for each value of the grid


def tune_alpha(points: DataFrame, queries: DataFrame, params: G.Params, k: int, widths: list[int], alphas: tuple[float, ...], target: float = 0.9) -> DataFrame:
    """(alpha, ndc, hops): the fixed variant's cost at ``target`` recall for a few values."""
    curves = stage(sweep(points, queries, [("fixed", a, params.tau) for a in alphas], params, k, widths), "alpha-curves")
    return _best(curves, "alpha", target)[1]
