"""The k best of a stated query set against all vectors, over the grid of query blocks and candidate shards.

A cell returns at most k rows for each query, and a window merges the shards.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from annspark.operators.grid import grid, walk
from annspark.plans.session import ship_package


def valid_vectors(df: DataFrame, nonzero: bool = False) -> DataFrame:
    """vec_id and embedding (doubles) of rows with an id and finite components only; with ``nonzero``, not all zero."""
    fine = F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") > 0)
    fine &= F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    if nonzero:
        fine &= F.exists("embedding", lambda x: x != 0)
    return df.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>")).where(fine)


def matrices(ids: pa.Array, lists: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, matrix) of rows for each vector length among them."""
    ids = ids.to_numpy(zero_copy_only=False)
    ends = lists.offsets.to_numpy()
    flat = lists.values.to_numpy(zero_copy_only=False)
    width = np.diff(ends)
    for d in np.unique(width):
        rows = np.flatnonzero(width == d)
        yield ids[rows], flat[ends[rows][:, None] + np.arange(d)]


class Best:
    """The k best hits of each query so far: larger scores first, then smaller ids.

    ``seen`` counts each query's reranked candidates, ``memo`` holds what a
    visit derives from its queries alone.
    """

    def __init__(self, n: int, k: int):
        self.k = k
        self.seen = np.zeros(n, np.int64)
        self.memo: dict = {}
        self.ids: list[np.ndarray] = [np.empty(0, np.int64)] * n
        self.scores: list[np.ndarray] = [np.empty(0)] * n

    def least(self, q: int) -> float:
        """A candidate below this score can't enter."""
        return self.scores[q][-1] if len(self.scores[q]) == self.k else -np.inf

    def add(self, q: int, ids: np.ndarray, scores: np.ndarray) -> None:
        if len(ids) > 8 * self.k:  # the rest can't be among the best
            cut = np.partition(scores, len(scores) - self.k)[len(scores) - self.k]
            ids, scores = ids[scores >= cut], scores[scores >= cut]
        ids, scores = np.concatenate([self.ids[q], ids]), np.concatenate([self.scores[q], scores])
        order = np.lexsort((ids, -scores))[: self.k]
        self.ids[q], self.scores[q] = ids[order], scores[order]


Visit = Callable[[np.ndarray, np.ndarray, np.ndarray, np.ndarray, Best], None]


def search(candidates: DataFrame, queries: DataFrame, k: int, visit: Visit, score_type: str, counted: bool = False) -> DataFrame:
    """(query_id, rank, vec_id, score) of the k best candidates that ``visit`` finds for each query.

    ``visit(query ids, queries, candidate ids, candidates, best)`` adds the hits
    of one batch of candidates. Of rows that repeat a query's id the smallest
    vector counts. ``counted`` adds n_candidates: how many were reranked.
    """
    ship_package(candidates.sparkSession)
    whole = score_type == "long"

    def found(block: dict[int, tuple[np.ndarray, np.ndarray, Best]]) -> Iterator[pa.RecordBatch]:
        for ids, _, best in block.values():
            n = [len(x) for x in best.ids]
            if not sum(n):
                continue
            scores = np.concatenate(best.scores).astype(np.int64 if whole else np.float64)
            seen = np.zeros(sum(n), np.int64)
            has = np.array(n) > 0
            seen[(np.cumsum(n) - n)[has]] = best.seen[has]  # on a query's first row
            columns = [pa.array(np.repeat(ids, n)), pa.array(np.concatenate(best.ids)), pa.array(scores, pa.int64() if whole else pa.float64()), pa.array(seen)]
            yield pa.RecordBatch.from_arrays(columns, ["query_id", "vec_id", "score", "seen"])

    def open_cell(parts) -> dict[int, tuple[np.ndarray, np.ndarray, Best]]:
        held: dict[int, tuple[list, list]] = {}
        for ids, m in (x for p in parts for x in matrices(*p)):
            got = held.setdefault(m.shape[1], ([], []))
            got[0].append(ids)
            got[1].append(m)
        return {d: (np.concatenate(i), np.concatenate(x), Best(sum(map(len, i)), k)) for d, (i, x) in held.items()}

    def meet(block, ids: pa.Array, vectors: pa.Array) -> Iterator[pa.RecordBatch]:
        for own, m in matrices(ids, vectors):
            if m.shape[1] in block:
                query_ids, wanted, best = block[m.shape[1]]
                visit(query_ids, wanted, own, m, best)
        return iter(())

    distinct = queries.groupBy("vec_id").agg(F.min("embedding").alias("embedding"))
    cells = grid(distinct, candidates.select("vec_id", "embedding"))
    hits = cells.mapInArrow(lambda batches: walk(batches, open_cell, meet, found), f"query_id long, vec_id long, score {score_type}, seen long")
    by = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    if counted:
        hits = hits.withColumn("n_candidates", F.sum("seen").over(W.partitionBy("query_id")))
    ranked = hits.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k)
    return ranked.select("query_id", "rank", "vec_id", "score", *(["n_candidates"] if counted else []))
