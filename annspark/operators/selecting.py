"""Neighbour selection over exact nearest candidates, as DataFrames."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from annspark.functions.graphs import Params
from annspark.functions.metric import Metric
from annspark.functions.rules import Rule
from annspark.functions.select import Selection, adaptive_select, select_neighbors
from annspark.operators.exact import exact_knn_graph
from annspark.plans.session import ship_package

CANDIDATES = "p long, pv array<double>, ids array<long>, dist array<double>, vecs array<double>"


def nearest_candidates(points: DataFrame, top: int) -> DataFrame:
    """(p, c): each point's ``top`` nearest others with their vectors, sorted by (distance, id)."""
    return candidates_of(points, exact_knn_graph(points, top))


def candidates_of(points: DataFrame, near: DataFrame) -> DataFrame:
    """(p, ids, dist, vecs) of the neighbours in ``near`` (src, dst, dist, rank), sorted by rank."""
    vec = points.select(F.col("vec_id").alias("dst"), F.col("embedding").cast("array<double>").alias("e"))
    rows = near.join(vec, "dst").groupBy(F.col("src").alias("p")).agg(F.array_sort(F.collect_list(F.struct("rank", "dst", "dist", "e"))).alias("c"))
    pick = lambda f: F.transform("c", lambda x: x[f])
    return rows.select("p", pick("dst").alias("ids"), pick("dist").alias("dist"), F.flatten(pick("e")).alias("vecs"))


def _each(candidates: DataFrame, choose, schema: str, emit) -> DataFrame:
    ship_package(candidates.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for p, ids, dist, vecs in zip(*(batch.column(i) for i in range(4))):
                ids, dist = np.array(ids.as_py(), np.int64), np.array(dist.as_py(), float)
                got = choose(dist, np.array(vecs.as_py(), float).reshape(len(ids), -1))
                rows += emit(p.as_py(), ids, dist, got)
            if rows:
                yield pa.RecordBatch.from_pylist(rows)

    return candidates.mapInArrow(run, schema)


def adaptive(points: DataFrame, top: int, p: Params, metric: Metric = Metric(), near: DataFrame | None = None) -> DataFrame:
    """(p, alpha_used, steps, n_kept, kept) of the adaptive selection over the nearest candidates, or over those in ``near``."""

    def emit(point: int, ids: np.ndarray, dist: np.ndarray, got: Selection) -> list[dict]:
        kept = ids[got.kept].tolist()
        return [{"p": point, "alpha_used": round(got.alpha_used, 6), "steps": got.steps, "n_kept": len(kept), "kept": ",".join(map(str, kept))}]

    choose = lambda d, v: adaptive_select(d, v, p.M, p.alpha0, p.alpha_max, p.alpha_step, p.tau, p.reuse, metric)
    out = _each(nearest_candidates(points, top) if near is None else candidates_of(points, near), choose, "p long, alpha_used double, steps long, n_kept long, kept string", emit)
    return out.select("p", "alpha_used", F.col("steps").cast("int"), F.col("n_kept").cast("int"), "kept")


def fixed(points: DataFrame, top: int, rule: Rule, cap: int, metric: Metric = Metric()) -> DataFrame:
    """(src, dst, dist, rank) of one rule with a cap over the nearest candidates."""

    def emit(point: int, ids: np.ndarray, dist: np.ndarray, got: Selection) -> list[dict]:
        return [{"src": point, "dst": int(ids[i]), "dist": float(dist[i]), "rank": r} for r, i in enumerate(got.kept, 1)]

    out = _each(nearest_candidates(points, top), lambda d, v: select_neighbors(d, v, rule, cap, metric), "src long, dst long, dist double, rank long", emit)
    return out.select("src", "dst", "dist", F.col("rank").cast("int"))


def work_ablation(points: DataFrame, top: int, p: Params, metric: Metric = Metric()) -> DataFrame:
    """(p, pairs_reused, pairs_plain, steps, distinct): distances between candidates with and without reuse."""

    def choose(d: np.ndarray, v: np.ndarray) -> tuple[Selection, Selection]:
        args = (p.M, p.alpha0, p.alpha_max, p.alpha_step, p.tau)
        return adaptive_select(d, v, *args, True, metric), adaptive_select(d, v, *args, False, metric)

    def emit(point: int, ids: np.ndarray, dist: np.ndarray, got) -> list[dict]:
        return [{"p": point, "pairs_reused": got[0].pairs, "pairs_plain": got[1].pairs, "steps": got[0].steps, "distinct": got[0].distinct}]

    return _each(nearest_candidates(points, top), choose, "p long, pairs_reused long, pairs_plain long, steps long, distinct long", emit)
