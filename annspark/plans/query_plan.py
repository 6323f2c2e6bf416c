"""Choosing how to answer a filtered nearest-neighbour query.

Spark has no access path for vector search, so the choice is made on the plan
of the request: few rows left by the filter are scanned exactly; otherwise the
index is searched for more than k and filtered after, and asked again with
twice as many until each query has its k or the index is exhausted.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from annspark.operators import exact
from annspark.operators.build import Router
from annspark.operators.search import search_index
from annspark.plans.session import stage


@dataclass(frozen=True)
class AnnQuery:
    """k nearest with an optional predicate over payload columns."""

    k: int
    width: int
    predicate: Column | None = None
    probes: int = 1
    metric: str = "l2"


def choose(n: int, kept: int, query: AnnQuery) -> str:
    """`scan` (no index worth it), `pre_filter` (scan what the filter leaves), `probe` or `post_filter`."""
    if n <= 4 * query.width:
        return "scan"
    if query.predicate is None:
        return "probe"
    return "pre_filter" if kept <= 10 * query.width else "post_filter"


def confirmed(query: AnnQuery, allowed: DataFrame, queries: DataFrame, found: DataFrame) -> DataFrame:
    """The exact answer: the index's k-th distance bounds a scan that finds what the search missed."""
    bounds = found.where(F.col("rank") == query.k).select("q_id", F.col("dist").alias("bound"))
    return exact.exact_knn(allowed, queries, query.k, query.metric, bounds=bounds)


def answer(query: AnnQuery, points: DataFrame, index: DataFrame, queries: DataFrame, router: Router | None = None) -> tuple[str, DataFrame]:
    """(strategy, (q_id, rank, vec_id, dist)). ``points`` has vec_id, embedding and payload columns."""
    allowed = points if query.predicate is None else points.where(query.predicate)
    n, kept = points.count(), allowed.count()
    how = choose(n, kept, query)
    if how in ("scan", "pre_filter"):
        return how, exact.exact_knn(allowed, queries, query.k, query.metric)
    if how == "probe":
        found = search_index(index, queries, query.k, [max(query.width, query.k)], router, query.probes, query.metric)
        return how, exact.top_k(found.select("q_id", "vec_id", "dist"), query.k)
    ids = stage(allowed.select("vec_id"), "filter-ids")
    need = min(query.k, kept)
    fetch = min(n, max(query.k, -(-query.k * n * 3 // (2 * max(1, kept)))))
    answers, left = None, stage(queries, "filter-queries")
    while True:
        found = search_index(index, left, fetch, [max(query.width, fetch)], router, query.probes, query.metric)
        good = stage(exact.top_k(found.select("q_id", "vec_id", "dist").join(ids, "vec_id", "left_semi"), query.k), "filter-found")
        full = good.groupBy("q_id").agg(F.count("*").alias("c")).where(F.col("c") >= need).select("q_id")
        done = good if fetch >= n else good.join(full, "q_id", "left_semi")
        answers = done if answers is None else answers.unionByName(done)
        if fetch >= n:
            return how, answers
        left = stage(left.join(full, "q_id", "left_anti"), "filter-left")
        if not left.take(1):
            return how, answers
        fetch = min(n, 2 * fetch)
