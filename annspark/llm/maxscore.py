"""Exact top-k search by integer inner product with MaxScore.

Terms are the vector's dimensions; a term's posting list is its column, in the
shard's order. In a shard every query term has an upper bound: the most its
column can add to the score. Terms are ordered by the spread of what they can
add. The essential ones are the least first terms after which the bounds of the
rest can no longer lift every candidate over the k-th best score; their postings
are traversed for all candidates. The other, non-essential terms are probed a
few at a time, and only for candidates whose sum so far plus the remaining
bounds can still enter. The threshold carries over from batch to batch of a
shard, and the shards' hits are merged.

Scores are exact: components are integers, sums of them stay exact in doubles
below 2**53, and larger ones are summed as 64-bit integers (a score that needs
more than 64 bits has no defined value).

Defined cases: vectors that are null, empty or hold null or non-finite
components take no part; only vectors of the query's length are its candidates;
repeated rows count each as candidates and once as a query; ties go to smaller
ids; no queries or no candidates give no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.llm.vector_blocks import Best, search, valid_vectors
from annspark.sources.tables import table

SCALE = 256
TOP = 5
QUERY_EVERY = 50
#: Non-essential terms are probed so many at a time.
STEP = 8
#: Candidates that set a first threshold.
FIRST = 64


def visit(query_ids: np.ndarray, queries: np.ndarray, ids: np.ndarray, rows: np.ndarray, best: Best) -> None:
    """Add the best of one batch of integer rows for every query."""
    n, d = rows.shape
    bound = float(np.abs(queries).max(initial=0)) * float(np.abs(rows).max(initial=0)) * d
    if bound >= 2**53:
        queries, rows = queries.astype(np.int64), rows.astype(np.int64)
    postings = np.asfortranarray(rows)
    top, low = rows.max(axis=0), rows.min(axis=0)
    order_of_ids = np.argsort(ids, kind="stable")
    sorted_ids = ids[order_of_ids]
    for q in range(len(query_ids)):
        w = queries[q]
        most, least = np.maximum(w * top, w * low), np.minimum(w * top, w * low)
        terms = np.argsort(least - most, kind="stable")
        rest = np.concatenate([np.cumsum(most[terms][::-1])[::-1], [0]])  # bounds of the terms from each place on
        alive = np.arange(n)
        s, e = np.searchsorted(sorted_ids, [query_ids[q], query_ids[q] + 1])
        if e > s:
            alive = np.delete(alive, order_of_ids[s:e])
        if best.least(q) == -np.inf and len(alive):
            first, alive = alive[:FIRST], alive[FIRST:]
            best.add(q, ids[first], rows[first] @ w)
        if not len(alive):
            continue
        threshold = best.least(q)
        floor = np.cumsum(least[terms])
        # Essential: the fewest terms after which the least sum plus the rest falls below the threshold.
        below = np.flatnonzero(floor + rest[1:] < threshold)
        essential = int(below[0]) + 1 if len(below) else d
        cols = terms[:essential]
        part = (postings[:, cols] @ w[cols])[alive]
        at = essential
        while True:
            keep = part + rest[at] >= threshold
            alive, part = alive[keep], part[keep]
            if at == d or not len(alive):
                break
            cols = terms[at : at + STEP]
            part = part + postings[np.ix_(alive, cols)] @ w[cols]
            at = min(d, at + STEP)
        if len(alive):
            best.add(q, ids[alive], part)


def integer_vectors(df: DataFrame) -> DataFrame:
    """Valid vectors with floor(SCALE * x) for each component x."""
    return valid_vectors(df).select("vec_id", F.transform("embedding", lambda x: F.floor(x * F.lit(float(SCALE))).cast("double")).alias("embedding"))


def top_k(candidates: DataFrame, queries: DataFrame, k: int = TOP) -> DataFrame:
    """(query_id, rank, vec_id, score) by inner product of integer components, never a query's own row."""
    return search(candidates, queries, k, visit, "long")


def op9_maxscore_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: query_id, rank, vec_id, score of the 5 largest integer inner products."""
    rows = integer_vectors(table(spark, sf_dir, "embeddings"))
    return top_k(rows, rows.where(F.pmod(F.col("vec_id"), F.lit(QUERY_EVERY)) == 0))


ORACLE = f"""
WITH v AS (
    SELECT vec_id, [CAST(floor(CAST(x AS DOUBLE) * {SCALE}) AS BIGINT) FOR x IN embedding] AS e FROM embeddings
    WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
      AND len([1 FOR x IN embedding IF x IS NULL OR isnan(x) OR isinf(x)]) = 0
), s AS (
    SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_dot_product(CAST(q.e AS DOUBLE[]), CAST(c.e AS DOUBLE[])) AS BIGINT) AS score
    FROM (SELECT * FROM v WHERE vec_id % {QUERY_EVERY} = 0) q JOIN v c ON c.vec_id <> q.vec_id AND len(c.e) = len(q.e)
), r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= {TOP}
"""
