"""Exact k nearest neighbours by scan: truth for every measure, and a baseline.

Queries and base rows meet in a grid of bounded blocks; a cell returns at most k
rows for each query, and a window merges.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from annspark.functions.metric import Metric
from annspark.operators.grid import grid, walk
from annspark.plans.session import ship_package, stage

#: Pairs of one Arrow batch of all_distances, at most about so many.
PAIR_BLOCK = 100_000
#: Pivots of a range join, at most so many: each left row is measured against all of them.
MOST_PIVOTS = 256
RESULT = "q_id long, rank int, vec_id long, dist double"


def to_matrix(column: pa.Array) -> np.ndarray:
    """Rows of a list column of equal lengths as doubles."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(n, -1) if n else np.empty((0, 0))


def as_queries(points: DataFrame) -> DataFrame:
    return points.select(F.col("vec_id").alias("q_id"), F.col("embedding").alias("qvec"))


def top_k(found: DataFrame, k: int) -> DataFrame:
    """The k nearest of each query over all parts, by (distance, id)."""
    by = W.partitionBy("q_id").orderBy("dist", "vec_id")
    return found.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k).select("q_id", "rank", "vec_id", "dist")


def _search_cells(space: Metric, k: int, skip_self: bool, bounded: bool):
    """How a cell of queries meets rows: a function over Arrow batches of sorted cells that returns each query's k nearest in each cell."""

    class Cell:
        def __init__(self, parts):
            self.ids = np.concatenate([p[0].to_numpy() for p in parts])
            q = np.concatenate([to_matrix(p[1]) for p in parts])
            self.known = q[:, -1] if bounded else None
            self.q = space.prepare(q[:, :-1] if bounded else q)
            self.best_i, self.best_d = np.full((len(self.ids), 0), -1, np.int64), np.full((len(self.ids), 0), np.inf)

    def visit(cell: Cell, ids: pa.Array, vectors: pa.Array) -> Iterator[pa.RecordBatch]:
        bound = cell.best_d[:, -1] if cell.best_d.shape[1] == k else None
        if cell.known is not None:
            bound = cell.known if bound is None else np.minimum(bound, cell.known)
        got_i, got_d = space.nearest(cell.q, space.prepare(to_matrix(vectors)), ids.to_numpy(), k, cell.ids if skip_self else None, bound=bound)
        best_i, best_d = np.concatenate([cell.best_i, got_i], axis=1), np.concatenate([cell.best_d, got_d], axis=1)
        order = np.lexsort((best_i, best_d), axis=1)[:, :k]
        cell.best_i, cell.best_d = np.take_along_axis(best_i, order, 1), np.take_along_axis(best_d, order, 1)
        return iter(())

    def close(cell: Cell) -> Iterator[pa.RecordBatch]:
        there = np.isfinite(cell.best_d)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(cell.ids, there.sum(axis=1))), pa.array(cell.best_i[there]), pa.array(cell.best_d[there])], ["q_id", "vec_id", "dist"])

    return lambda batches: walk(batches, Cell, visit, close)


def _with_bound(queries: DataFrame, bounds: DataFrame) -> DataFrame:
    """Queries whose bound travels as a last component."""
    last = F.array(F.coalesce("bound", F.lit(float("inf"))))
    return queries.select("q_id", "qvec").join(bounds.select("q_id", "bound"), "q_id", "left").select("q_id", F.concat(F.col("qvec").cast("array<double>"), last).alias("qvec"))


def exact_knn(base: DataFrame, queries: DataFrame, k: int, metric: str = "l2", skip_self: bool = False, bounds: DataFrame | None = None) -> DataFrame:
    """(q_id, rank, vec_id, dist); with ``skip_self`` a query isn't its own neighbour.

    ``bounds`` has (q_id, bound): a distance within which a query is known to have k neighbours, so that the scan keeps no row beyond.
    """
    ship_package(base.sparkSession)
    asked = queries.select("q_id", "qvec") if bounds is None else _with_bound(queries, bounds)
    found = grid(asked, base.select("vec_id", "embedding"))
    return top_k(found.mapInArrow(_search_cells(Metric(metric), k, skip_self, bounds is not None), "q_id long, vec_id long, dist double"), k)


class Boxes:
    """Boxes that cover the space, from halving a sample at medians along its widest side; a box takes values up to its upper ends."""

    def __init__(self, x: np.ndarray, count: int):
        dim = x.shape[1]
        self.splits: list[tuple[int, float, int, int]] = []
        low, high, leaf = [], [], []

        def halve(own: np.ndarray, lo: np.ndarray, hi: np.ndarray, parts: int) -> int:
            """The number of a node: splits count from 0, boxes from -1 downwards."""
            values = x[own]
            side = int(np.argmax(values.max(axis=0) - values.min(axis=0))) if len(own) else 0
            cut = float(np.partition(values[:, side], (len(own) - 1) // 2)[(len(own) - 1) // 2]) if len(own) else 0.0
            below = values[:, side] <= cut if len(own) else np.zeros(0, bool)
            if parts < 2 or len(own) < 2 or below.all():
                low.append(lo), high.append(hi), leaf.append(len(own))
                return -len(low)
            at = len(self.splits)
            self.splits.append((side, cut, 0, 0))
            top, bottom = hi.copy(), lo.copy()
            top[side], bottom[side] = cut, cut
            self.splits[at] = (side, cut, halve(own[below], lo, top, parts // 2), halve(own[~below], bottom, hi, parts - parts // 2))
            return at

        self.root = halve(np.arange(len(x)), np.full(dim, -np.inf), np.full(dim, np.inf), count)
        self.low, self.high = np.array(low), np.array(high)

    def of(self, x: np.ndarray) -> np.ndarray:
        """The box of each row."""
        out = np.empty(len(x), np.int32)
        todo = [(self.root, np.arange(len(x)))]
        while todo:
            node, own = todo.pop()
            if node < 0:
                out[own] = -node - 1
                continue
            side, cut, left, right = self.splits[node]
            below = x[own, side] <= cut
            todo += [(left, own[below]), (right, own[~below])]
        return out

    def within(self, q: np.ndarray, bound: np.ndarray, block: int = 1024) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(rows, boxes): every box that a ball around a row can touch."""
        for i in range(0, len(q), block):
            part, gap = q[i : i + block], 0.0
            for j in range(q.shape[1]):
                off = np.maximum(np.maximum(self.low[:, j] - part[:, j, None], part[:, j, None] - self.high[:, j]), 0)
                gap = gap + off * off
            row, box = np.nonzero(gap <= (bound[i : i + block, None] * (1 + 1e-9)) ** 2)
            yield row + i, box.astype(np.int32)


#: Rows of a box, about so many, and points of the sample that places boxes for each of them.
BOX_ROWS, BOX_SAMPLE = 16_384, 64


def exact_knn_boxes(base: DataFrame, queries: DataFrame, k: int, box_rows: int | None = None, skip_self: bool = False) -> DataFrame:
    """exact_knn (Euclidean) for vectors of few components: a query scans its own box, then the boxes within the k-th distance found there.

    The sample only balances boxes. Queries and rows are written once between the two rounds.
    """
    spark = base.sparkSession
    ship_package(spark)
    n = base.count()
    count = max(1, -(-n // (box_rows or BOX_ROWS)))
    part = F.pmod(F.xxhash64("vec_id", F.lit(23)), F.lit(1_000_000)) < int(min(1.0, BOX_SAMPLE * max(count, 64) / max(1, n)) * 1_000_000)
    sample = base.where(part).select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>")).orderBy("vec_id").toArrow()
    if not sample.num_rows:
        return exact_knn(base, queries, k, skip_self=skip_self)
    boxes = spark.sparkContext.broadcast(Boxes(to_matrix(sample.column(1)), count))
    kind, names = "block int, shard int, side int, id long, vec array<double>", ["block", "shard", "side", "id", "vec"]

    def cells(batch: pa.RecordBatch, row: np.ndarray, box: np.ndarray, side: int) -> pa.RecordBatch:
        zeros = np.zeros(len(row), np.int32)
        return pa.RecordBatch.from_arrays([pa.array(box), pa.array(zeros), pa.array(zeros + np.int32(side)), batch.column(0).take(pa.array(row)), batch.column(1).take(pa.array(row))], names)

    def place(side: int):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    yield cells(batch, np.arange(batch.num_rows), boxes.value.of(to_matrix(batch.column(1))), side)

        return run

    def around(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                q = to_matrix(batch.column(1))
                own = boxes.value.of(q[:, :-1])
                for row, box in boxes.value.within(q[:, :-1], q[:, -1]):
                    other = box != own[row]
                    yield cells(batch, row[other], box[other], 0)

    def meet(asked: DataFrame, bounded: bool) -> DataFrame:
        both = asked.unionByName(rows).repartition(max(count, 2 * spark.sparkContext.defaultParallelism), "block").sortWithinPartitions("block", "side")
        return both.mapInArrow(_search_cells(Metric(), k, skip_self, bounded), "q_id long, vec_id long, dist double")

    pick = lambda df, i, v: df.select(F.col(i).cast("long").alias("id"), F.col(v).cast("array<double>").alias("vec"))
    rows = stage(pick(base, "vec_id", "embedding").mapInArrow(place(1), kind), "box-rows")
    asked = stage(queries.select("q_id", "qvec"), "box-queries")
    first = stage(meet(pick(asked, "q_id", "qvec").mapInArrow(place(0), kind), False), "box-first")
    bounds = first.groupBy("q_id").agg(F.when(F.count("*") >= k, F.max("dist")).alias("bound"))
    second = meet(pick(_with_bound(asked, bounds), "q_id", "qvec").mapInArrow(around, kind), True)
    return top_k(first.unionByName(second), k)


def all_distances(base: DataFrame, queries: DataFrame, metric: str = "l2") -> DataFrame:
    """(q_id, vec_id, dist) of all queries and base rows; the rows are streamed and never held together."""
    ship_package(base.sparkSession)
    space = Metric(metric)

    def open_cell(parts):
        return np.concatenate([p[0].to_numpy() for p in parts]), space.prepare(np.concatenate([to_matrix(p[1]) for p in parts]))

    def visit(cell, ids: pa.Array, vectors: pa.Array) -> Iterator[pa.RecordBatch]:
        q_ids, q = cell
        b_ids, x = ids.to_numpy(), space.prepare(to_matrix(vectors))
        step = max(1, PAIR_BLOCK // len(b_ids))
        for i in range(0, len(q_ids), step):
            part = q_ids[i : i + step]
            d = space.cross(q[i : i + step], x)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(part, len(b_ids))), pa.array(np.tile(b_ids, len(part))), pa.array(d.ravel())], ["q_id", "vec_id", "dist"])

    met = grid(queries.select("q_id", "qvec"), base.select("vec_id", "embedding"))
    return met.mapInArrow(lambda batches: walk(batches, open_cell, visit), "q_id long, vec_id long, dist double")


def range_scan(left: DataFrame, right: DataFrame, tau: float) -> DataFrame:
    """(l_id, r_id, dist) of all pairs within ``tau`` (Euclidean) over a grid, for vectors of many components, which pivots hardly tell apart.

    A matrix product rules pairs out, and what it leaves is measured by direct differences.
    """
    ship_package(left.sparkSession)
    space = Metric()

    def open_cell(parts):
        x = np.concatenate([to_matrix(p[1]) for p in parts])
        return np.concatenate([p[0].to_numpy() for p in parts]), x, np.einsum("ij,ij->i", x, x)

    def visit(cell, ids: pa.Array, vectors: pa.Array) -> Iterator[pa.RecordBatch]:
        l_ids, x, xx = cell
        r_ids, y = ids.to_numpy(), to_matrix(vectors)
        yy = np.einsum("ij,ij->i", y, y)
        slack = 1e-9 * (float(xx.max()) + float(yy.max())) + 1e-300
        step = max(1, 2_000_000 // len(y))
        for i in range(0, len(x), step):
            coarse = x[i : i + step] @ (-2 * y.T)
            coarse += yy
            row, col = np.nonzero(coarse <= (tau * tau + slack - xx[i : i + step])[:, None])
            for j in range(0, len(row), PAIR_BLOCK):
                l, r = row[j : j + PAIR_BLOCK] + i, col[j : j + PAIR_BLOCK]
                d = space.rows(x[l], y[r])
                near = d <= tau
                yield pa.RecordBatch.from_arrays([pa.array(l_ids[l[near]]), pa.array(r_ids[r[near]]), pa.array(d[near])], ["l_id", "r_id", "dist"])

    met = grid(left.select("vec_id", "embedding"), right.select("vec_id", "embedding"))
    return met.mapInArrow(lambda batches: walk(batches, open_cell, visit), "l_id long, r_id long, dist double")


def exact_knn_graph(points: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """(src, dst, dist, rank): every point with its k nearest others."""
    return exact_knn(points, as_queries(points), k, metric, skip_self=True).select(F.col("q_id").alias("src"), F.col("vec_id").alias("dst"), "dist", "rank")


def range_join(left: DataFrame, right: DataFrame, tau: float, pivots: int | None = None, metric: str = "l2") -> DataFrame:
    """(l_id, r_id, dist) of all pairs within ``tau``, through pivots and annuli.

    Without a number of pivots there are as many as the square root of the right side's rows, from 16 to MOST_PIVOTS.

    Each point belongs to its nearest pivot's cell of ``right``; a left point can
    only meet cells whose pivot distances differ by at most tau from its own
    (triangle inequality). Cells are cut into annuli of width tau, so pairs meet
    by equality of (pivot, annulus), and the rest is checked exactly.
    """
    if tau <= 0:
        raise ValueError("tau must be positive")
    spark = left.sparkSession
    ship_package(spark)
    space = Metric(metric)
    pivots = pivots or int(min(MOST_PIVOTS, max(16, right.count() ** 0.5)))
    # A bounded sample: the pivots' only purpose is to balance cells.
    sample = right.select("vec_id", "embedding").orderBy(F.xxhash64("vec_id"), "vec_id").limit(pivots).toArrow()
    if not sample.num_rows:
        return spark.createDataFrame([], "l_id long, r_id long, dist double")
    shared = spark.sparkContext.broadcast(space.prepare(to_matrix(sample.column(1))))

    def place(all_pivots: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if not batch.num_rows:
                    continue
                x = space.prepare(to_matrix(batch.column(1)))
                d = space.cross(x, shared.value)
                n, p = d.shape
                if all_pivots:
                    row, pivot = np.repeat(np.arange(n), p), np.tile(np.arange(p), n)
                else:
                    row, pivot = np.arange(n), d.argmin(axis=1)
                gap = d[row, pivot]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(pa.array(row)), batch.column(1).take(pa.array(row)), pa.array(pivot.astype(np.int32)), pa.array(np.floor(gap / tau).astype(np.int64)), pa.array(gap)],
                    ["id", "e", "pivot", "ring", "gap"],
                )

        return run

    kind = "id long, e array<double>, pivot int, ring long, gap double"
    pick = lambda df: df.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>"))
    r = pick(right).mapInArrow(place(False), kind).select(F.col("id").alias("r_id"), F.col("e").alias("re"), "pivot", "ring", F.col("gap").alias("r_gap"))
    used = r.groupBy("pivot").agg(F.min("ring").alias("low"), F.max("ring").alias("high"))
    around = pick(left).mapInArrow(place(True), kind).join(F.broadcast(used), "pivot").where("ring BETWEEN low - 1 AND high + 1")
    l = around.select(F.col("id").alias("l_id"), F.col("e").alias("le"), "pivot", F.col("gap").alias("l_gap"), F.explode(F.sequence(F.col("ring") - 1, F.col("ring") + 1)).alias("ring"))
    near = l.join(r, ["pivot", "ring"]).where(F.abs(F.col("l_gap") - F.col("r_gap")) <= tau * (1 + 1e-12))

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                d = space.rows(space.prepare(to_matrix(batch.column(1))), space.prepare(to_matrix(batch.column(3))))
                out = pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(d)], ["l_id", "r_id", "dist"])
                yield out.filter(pa.array(d <= tau))

    return near.select("l_id", "le", "r_id", "re").mapInArrow(check, "l_id long, r_id long, dist double")
