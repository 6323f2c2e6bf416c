"""Approximate nearest neighbours by cross-polytope hashing.

A pseudo-rotation is three rounds of random signs and a fast Hadamard transform
on the vector padded to a power of two. Its hash is the nearest signed axis:
the largest component by size, with its sign. A table joins the hashes of two
rotations, and each of TABLES tables holds every vector. A query probes the
PROBES buckets of each table whose two axes it is nearest to, by the sum of its
two components, and the union of what lies there is reranked by exact cosine on
the original vectors in double precision. A query that finds fewer than k so,
over all shards, is ranked against every candidate of its length.

The index covers every row and fits nothing: rotations come from a seed alone.
Each shard holds its own tables, and shards are merged.

Defined cases: vectors that are null, empty, zero or hold null or non-finite
components take no part; only vectors of the query's length are its candidates;
repeated rows count each as candidates and once as a query; ties go to smaller
ids; no queries or no candidates give no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.llm.vector_blocks import Best, search, valid_vectors
from annspark.plans.session import stage
from annspark.sources.tables import table

TABLES = 48
PROBES = 48
#: Queries that are marked together.
CHUNK = 256
TOP = 5
QUERY_EVERY = 50
SEED = 7
SIGN_ROUNDS = 3


def hadamard(x: np.ndarray) -> np.ndarray:
    """The unnormalised Walsh-Hadamard transform of each row; the width is a power of two."""
    n, d = x.shape
    h = 1
    while h < d:
        y = x.reshape(n, d // (2 * h), 2, h)
        x = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], axis=2).reshape(n, d)
        h *= 2
    return x


@lru_cache(maxsize=8)
def signs(tables: int, width: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).choice(np.array([-1.0, 1.0], np.float32), (tables, SIGN_ROUNDS, width))


def rotated(x: np.ndarray, count: int, seed: int = SEED) -> Iterator[np.ndarray]:
    """Rows under one pseudo-rotation after another: (rows, padded width)."""
    n, d = x.shape
    width = 1 << max(0, (d - 1).bit_length())
    unit = np.zeros((n, width), np.float32)
    unit[:, :d] = x / np.linalg.norm(x, axis=1, keepdims=True).clip(1e-300)
    for rounds in signs(count, width, seed):
        y = unit
        for s in rounds / np.float32(np.sqrt(width)):
            y = hadamard(y * s)
        yield y


def nearest_axis(y: np.ndarray) -> np.ndarray:
    """The nearest signed axis of each rotated row: 2 * axis + (1 if negative)."""
    at = np.abs(y).argmax(axis=1)
    return 2 * at + (np.take_along_axis(y, at[:, None], axis=1)[:, 0] < 0)


def codes(x: np.ndarray, tables: int, seed: int = SEED) -> np.ndarray:
    """The bucket of each row in each table: (tables, rows)."""
    turns = rotated(x, 2 * tables, seed)
    return np.stack([nearest_axis(y) * 2 * y.shape[1] + nearest_axis(next(turns)) for y in turns])


def probes(x: np.ndarray, tables: int, count: int, seed: int = SEED) -> np.ndarray:
    """The ``count`` nearest buckets of each row in each table: (tables, rows, count), fewer where there are fewer pairs of axes.

    Of axes in the order of nearness only pairs of ranks i, j with (i + 1)(j + 1)
    up to ``count`` can be among the nearest.
    """
    turns = rotated(x, 2 * tables, seed)
    out = []
    for pair in zip(turns, turns):
        width = pair[0].shape[1]
        order = [np.argsort(-np.abs(y), axis=1, kind="stable") for y in pair]
        sizes = [np.take_along_axis(np.abs(y), o, axis=1) for y, o in zip(pair, order)]
        axis = [2 * o + (np.take_along_axis(y, o, axis=1) < 0) for y, o in zip(pair, order)]
        i, j = np.nonzero(np.multiply.outer(np.arange(1, width + 1), np.arange(1, width + 1)) <= count)
        near = np.argsort(-(sizes[0][:, i] + sizes[1][:, j]), axis=1, kind="stable")[:, :count]
        out.append(np.take_along_axis(axis[0][:, i] * 2 * width + axis[1][:, j], near, axis=1).astype(np.int32))
    return np.stack(out)


def add_cosines(best: Best, q: int, w: np.ndarray, ids: np.ndarray, rows: np.ndarray, norms: np.ndarray) -> None:
    best.seen[q] += len(ids)
    if len(ids):
        best.add(q, ids, (rows * w).sum(axis=1) / (norms * np.sqrt((w * w).sum())))


def visit_all(query_ids: np.ndarray, queries: np.ndarray, ids: np.ndarray, rows: np.ndarray, best: Best) -> None:
    """Every candidate is a hit."""
    norms = np.sqrt((rows * rows).sum(axis=1))
    for q, me in enumerate(query_ids):
        at = np.flatnonzero(ids != me)
        add_cosines(best, q, queries[q], ids[at], rows[at], norms[at])


def make_visit(tables: int, count: int, seed: int):
    def visit(query_ids: np.ndarray, queries: np.ndarray, ids: np.ndarray, rows: np.ndarray, best: Best) -> None:
        n = len(ids)
        if "probes" not in best.memo:
            best.memo["probes"] = probes(queries, tables, count, seed)
        probe = best.memo["probes"]
        code = codes(rows, tables, seed)
        order = np.argsort(code, axis=1, kind="stable")
        norms = np.sqrt((rows * rows).sum(axis=1))
        for low in range(0, len(query_ids), CHUNK):
            chunk = np.arange(low, min(low + CHUNK, len(query_ids)))
            hit = np.zeros((len(chunk), n), bool)
            for t in range(tables):
                held = code[t][order[t]]
                wanted = probe[t, chunk].ravel()
                start, stop = np.searchsorted(held, wanted, "left"), np.searchsorted(held, wanted, "right")
                size = stop - start
                place = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size) + np.repeat(start, size)
                hit[np.repeat(np.repeat(np.arange(len(chunk)), probe.shape[2]), size), order[t][place]] = True
            for q in chunk:
                at = np.flatnonzero(hit[q - low] & (ids != query_ids[q]))
                add_cosines(best, q, queries[q], ids[at], rows[at], norms[at])

    return visit


def nearest(candidates: DataFrame, queries: DataFrame, k: int = TOP, tables: int = TABLES, count: int = PROBES, seed: int = SEED) -> DataFrame:
    """(query_id, rank, vec_id, score, n_candidates) of the k largest cosines found, never a query's own row; all candidates where they are fewer.

    n_candidates is how many rows were reranked for the query.
    """
    found = stage(search(candidates, queries, k, make_visit(tables, count, seed), "double", counted=True), "polytope-found")
    full = found.where(F.col("rank") == k).select(F.col("query_id").alias("vec_id"))
    short = stage(queries.join(full, "vec_id", "left_anti"), "polytope-short")
    if not short.take(1):
        return found
    rest = search(candidates, short, k, visit_all, "double", counted=True)
    return found.join(full.select(F.col("vec_id").alias("query_id")), "query_id", "left_semi").unionByName(rest)


def op10_cross_polytope(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: query_id, rank, vec_id, score of the 5 nearest found; and n_candidates, how many rows were reranked."""
    rows = valid_vectors(table(spark, sf_dir, "embeddings"), nonzero=True)
    return nearest(rows, rows.where(F.pmod(F.col("vec_id"), F.lit(QUERY_EVERY)) == 0))
