"""The guarantees as queries: each returns its violations or the quantities it bounds."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from annspark.functions.balls import FEW_COMPONENTS, Balls, Near
from annspark.functions.metric import Metric
from annspark.operators import exact
from annspark.operators.build import lists_of, vectors_in_order
from annspark.operators.exact import to_matrix
from annspark.operators.grid import grid, walk
from annspark.plans.session import ship_package, stage

#: Slack for comparisons of sums of distances.
EPS = 1e-9


def pair_distances(points: DataFrame) -> DataFrame:
    """(src, dst, dist) of all ordered pairs."""
    pairs = exact.all_distances(points, exact.as_queries(points))
    return pairs.where("q_id <> vec_id").select(F.col("q_id").alias("src"), F.col("vec_id").alias("dst"), "dist")


def aspect_ratio(points: DataFrame) -> DataFrame:
    """(diameter, smallest, ratio) over the positive distances of all pairs; a task returns two numbers for each block of points."""
    ship_package(points.sparkSession)
    # Copies are at distance zero and have no other distances than their first.
    rows = stage(points.select("vec_id", F.col("embedding").cast("array<double>")).groupBy("embedding").agg(F.min("vec_id").alias("vec_id")), "extreme-points")
    space = Metric()

    class Cell:
        def __init__(self, parts):
            self.x, self.high, self.low = np.concatenate([to_matrix(p[1]) for p in parts]), 0.0, np.inf

    def visit(cell: Cell, ids: pa.Array, vectors: pa.Array) -> Iterator[pa.RecordBatch]:
        cell.high, cell.low = space.extremes(cell.x, to_matrix(vectors), cell.high, cell.low)
        return iter(())

    def close(cell: Cell) -> Iterator[pa.RecordBatch]:
        if cell.high > 0:
            yield pa.RecordBatch.from_arrays([pa.array([cell.high]), pa.array([cell.low])], ["high", "low"])

    points = rows.select("vec_id", "embedding")
    out = grid(points, points).mapInArrow(lambda batches: walk(batches, Cell, visit, close), "high double, low double")
    ext = out.agg(F.max("high").alias("diameter"), F.min("low").alias("smallest"))
    return ext.select("diameter", "smallest", (F.col("diameter") / F.col("smallest")).alias("ratio"))


def query_distances(points: DataFrame, queries: DataFrame) -> DataFrame:
    """(q_id, vec_id, dist) of all queries and points."""
    return exact.all_distances(points, queries)


def reducible_violations(edges: DataFrame, distances: DataFrame, alpha: float, tau: float) -> DataFrame:
    """(q_id, p) where d(q, nearest) <= tau, p isn't the nearest, and no edge of p is exact or alpha times closer. Must be empty."""
    near = distances.groupBy("q_id").agg(F.min(F.struct("dist", "vec_id")).alias("m")).select("q_id", F.col("m.vec_id").alias("v"), F.col("m.dist").alias("vd"))
    state = distances.join(F.broadcast(near), "q_id").where((F.col("vd") <= tau) & (F.col("vec_id") != F.col("v")) & (F.col("dist") > F.col("vd")))
    state = state.select("q_id", F.col("vec_id").alias("p"), F.col("dist").alias("pd"), "v")
    step = edges.select(F.col("src").alias("p"), F.col("dst").alias("n")).join(distances.select("q_id", F.col("vec_id").alias("n"), F.col("dist").alias("nd")), "n")
    good = state.join(step, ["q_id", "p"]).where((F.col("n") == F.col("v")) | (F.col("nd") <= F.col("pd") / alpha + EPS)).select("q_id", "p").distinct()
    return state.select("q_id", "p").join(good, ["q_id", "p"], "left_anti")


def shortcut_violations(edges: DataFrame, pairs: DataFrame, alpha: float, tau: float) -> DataFrame:
    """(p, z) that are no edge although no out-neighbour n of p has d(p, z) > alpha d(n, z) + (alpha + 1) tau. Must be empty."""
    missing = pairs.select(F.col("src").alias("p"), F.col("dst").alias("z"), F.col("dist").alias("pz")).join(edges.select(F.col("src").alias("p"), F.col("dst").alias("z")), ["p", "z"], "left_anti")
    step = edges.select(F.col("src").alias("p"), F.col("dst").alias("n")).join(pairs.select(F.col("src").alias("n"), F.col("dst").alias("z"), F.col("dist").alias("nz")), "n")
    good = missing.join(step, ["p", "z"]).where(F.col("pz") > alpha * F.col("nz") + (alpha + 1) * tau - EPS).select("p", "z").distinct()
    return missing.select("p", "z").join(good, ["p", "z"], "left_anti")


def packing_violations(edges: DataFrame, pairs: DataFrame, alpha: float, tau: float) -> DataFrame:
    """(src, u, v): kept pairs closer to each other than the rule allows. Must be empty."""
    a = edges.select("src", F.col("dst").alias("u"), F.col("dist").alias("du"))
    b = edges.select("src", F.col("dst").alias("v"), F.col("dist").alias("dv"))
    both = a.join(b, "src").where("u < v").join(pairs.select(F.col("src").alias("u"), F.col("dst").alias("v"), F.col("dist").alias("uv")), ["u", "v"])
    return both.where(F.greatest("du", "dv") > alpha * F.col("uv") + (alpha + 1) * tau + EPS).select("src", "u", "v")


#: Kept neighbours that a point's open queries are measured against at a time, the farthest first.
KEPT_BLOCK = 64


def violations(points: DataFrame, edges: DataFrame, queries: DataFrame, alpha: float, tau: float, statement: str) -> DataFrame:
    """The rows of reducible_violations (q_id, p) or shortcut_violations (p, z), the queries then being the points.

    A point's edges (or a row of lists) are one row: its far neighbours first answer whole balls of queries, then the
    queries that are left are measured, until none is open or all neighbours were asked. No pair is written, and no
    graph is collected; vectors of points and queries are broadcast.
    """
    spark = points.sparkSession
    ship_package(spark)
    space, shift, reducible = Metric(), (alpha + 1) * tau, statement == "reducible"
    ids, _, x = vectors_in_order(points, space)
    asked = queries.select(F.col("q_id").cast("long"), F.col("qvec").cast("array<double>")).orderBy("q_id").toArrow()
    q_ids, q = asked.column(0).to_numpy(), to_matrix(asked.column(1))
    target, near = np.searchsorted(ids, q_ids), np.zeros(len(q_ids))
    if reducible and len(q):
        found = (exact.exact_knn_boxes if x.shape[1] <= FEW_COMPONENTS else exact.exact_knn)(points, queries, 1)
        target = np.searchsorted(ids, found.orderBy("q_id").select("vec_id").toArrow().column(0).to_numpy())
        near = space.rows(q, x[target])
    shared = spark.sparkContext.broadcast((ids, x, q_ids, q, target, near))
    names = ["q_id", "p"] if reducible else ["z", "p"]

    def answered(d: np.ndarray, least: np.ndarray, more: float = 0.0) -> np.ndarray:
        """Whether a query at a distance ``d`` has a neighbour of the point that is near enough; ``more`` is added to both distances' worse sides."""
        return least + more <= (d - more) / alpha + EPS if reducible else d - more > alpha * (least + more) + shift - EPS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x, q_ids, q, target, near = shared.value
        balls, to = Balls(q), Near(x)
        centres, own = to.of(balls.centre), to.of(q)
        edge = np.zeros(len(ids), bool)

        def broken(p: int, kept: np.ndarray) -> np.ndarray:
            """The queries for which a point with neighbours ``kept`` breaks the statement."""
            kept = kept[np.argsort(-space.rows(x[kept], x[p]), kind="stable")]
            left = np.arange(len(balls.size))
            if len(kept):
                # No more than these bounds allow, less twice the slack that the statements have.
                high = to.least(*centres, kept[:KEPT_BLOCK])[1] + 3 * EPS
                left = left[~answered(space.rows(balls.centre, x[p]), high, balls.radius)]
            rows = balls.members(left)
            d = space.rows(q[rows], x[p])
            edge[kept] = True
            open_ = ~edge[target[rows]] & (target[rows] != p)
            edge[kept] = False
            if reducible:
                open_ &= (near[rows] <= tau) & (d > near[rows])
            rows, d = rows[open_], d[open_]
            for i in range(0, len(kept), KEPT_BLOCK):
                if not len(rows):
                    break
                some = kept[i : i + KEPT_BLOCK]
                low, high = to.least(own[0][rows], own[1][rows], some)
                good = answered(d, high)
                unsure = np.flatnonzero(answered(d, low) & ~good)
                good[unsure] = answered(d[unsure], space.cross(q[rows[unsure]], x[some]).min(axis=1, initial=np.inf))
                rows, d = rows[~good], d[~good]
            return rows

        for batch in batches:
            flat = np.searchsorted(ids, batch.column(1).flatten().to_numpy())
            ends = np.concatenate([[0], np.cumsum(np.diff(batch.column(1).offsets.to_numpy()))])
            for src, i, j in zip(np.searchsorted(ids, batch.column(0).to_numpy()).tolist(), ends, ends[1:]):
                bad = broken(src, flat[i:j])
                if len(bad):
                    yield pa.RecordBatch.from_arrays([pa.array(q_ids[bad]), pa.array(np.full(len(bad), ids[src]))], names)

    rows = lists_of(edges).select("src", "nbrs")
    # A point without edges answers no query.
    bare = points.select(F.col("vec_id").cast("long").alias("src")).join(rows.select("src"), "src", "left_anti").withColumn("nbrs", F.array().cast("array<long>"))
    placed = rows.unionByName(bare).repartition(4 * spark.sparkContext.defaultParallelism, "src")
    return placed.mapInArrow(run, f"{names[0]} long, p long")


def close_kept(points: DataFrame, edges: DataFrame, alpha: float, tau: float) -> DataFrame:
    """The rows of packing_violations, a vertex at a time: its kept neighbours are measured against each other and no pair is joined.

    Two that are both within the shift break nothing, so each pair has a farther one.
    """
    spark = points.sparkSession
    ship_package(spark)
    space = Metric()
    ids, _, x = vectors_in_order(points, space)
    shared = spark.sparkContext.broadcast((ids, x))
    shift = (alpha + 1) * tau

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x = shared.value
        for batch in batches:
            kept, dists = (batch.column(c).flatten().to_numpy() for c in (1, 2))
            ends = np.concatenate([[0], np.cumsum(np.diff(batch.column(1).offsets.to_numpy()))])
            for src, s, e in zip(batch.column(0).to_pylist(), ends, ends[1:]):
                own, dist = kept[s:e], dists[s:e]
                at = x[np.searchsorted(ids, own)]
                far = np.flatnonzero(dist > shift + EPS)
                for i in range(0, len(far), KEPT_BLOCK):
                    some = far[i : i + KEPT_BLOCK]
                    over = np.maximum(dist[some, None], dist) > alpha * space.cross(at[some], at) + shift + EPS
                    # A pair of two far ones is met twice.
                    row, col = np.nonzero(over & (own[some, None] != own) & ((own[some, None] < own) | (dist <= shift + EPS)))
                    if len(row):
                        a, b = own[some[row]], own[col]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(a), src)), pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], ["src", "u", "v"])

    return lists_of(edges).mapInArrow(run, "src long, u long, v long")


def near_ring_counts(edges: DataFrame, pairs: DataFrame, alpha: float, tau: float) -> DataFrame:
    """(src, kept, packing): kept neighbours within 2 (alpha + 1) tau, and the points there, which bound them.

    With distances of at least one between points, a ball of fixed radius holds a fixed number of them at most.
    """
    near = 2 * (alpha + 1) * tau
    kept = edges.where(F.col("dist") <= near).groupBy("src").agg(F.count("*").alias("kept"))
    there = pairs.where(F.col("dist") <= near).groupBy("src").agg(F.count("*").alias("packing"))
    return there.join(kept, "src", "left").select("src", F.coalesce("kept", F.lit(0)).alias("kept"), "packing")


def hops_bound(routes: DataFrame, truth: DataFrame, alpha: float, tau: float, diameter: float, smallest: float) -> DataFrame:
    """(q_id, hops, bound, exact) of the queries within tau of the data: greedy must be exact within log_alpha(4 ratio) + 2 hops."""
    last = routes.groupBy("q_id").agg((F.max("hop") + 1).alias("hops"), F.max_by("vec_id", "hop").alias("answer"), F.max_by("dist", "hop").alias("got"))
    near = truth.where((F.col("rank") == 1) & (F.col("dist") <= tau)).select("q_id", "dist")
    bound = np.log(4 * diameter / smallest) / np.log(alpha) + 2 if alpha > 1 else float("inf")
    return near.join(last, "q_id").select("q_id", "hops", F.lit(float(bound)).alias("bound"), (F.abs(F.col("got") - F.col("dist")) <= EPS).alias("exact"))


def ratio_bound_violations(routes: DataFrame, truth: DataFrame, alpha: float) -> DataFrame:
    """(q_id, ratio) of queries whose local optimum is more than (alpha + 1) / (alpha - 1) times the nearest distance. Must be empty."""
    last = routes.groupBy("q_id").agg(F.min("dist").alias("got"))
    near = truth.where("rank = 1").select("q_id", F.col("dist").alias("true"))
    limit = (alpha + 1) / (alpha - 1)
    return near.join(last, "q_id").where(F.col("got") > limit * F.col("true") + EPS).select("q_id", (F.col("got") / F.col("true")).alias("ratio"))


#: Rows that a task of `spread` measures against all others at a time, and balls that a cover opens at a time.
SPREAD_BLOCK, COVER_BLOCK = 512, 128


def share_vectors(points: DataFrame, metric: str = "l2"):
    """A broadcast of all prepared vectors, ordered by a hash of the id."""
    spark = points.sparkSession
    ship_package(spark)
    rows = points.select("vec_id", F.col("embedding").cast("array<double>").alias("e")).orderBy(F.xxhash64("vec_id"), "vec_id").toArrow()
    return spark.sparkContext.broadcast(Metric(metric).prepare(to_matrix(rows.column(1))))


def diameter(points: DataFrame, dim: int) -> float | None:
    """The largest distance between two of ``points``, vectors of few components.

    A pair found by going from far row to far row bounds it from below. A row is left out if neither the corners of
    all rows' box nor the balls around the box's middle and the mean can be so far from it; the others meet in a grid.
    """
    part = [F.col("embedding")[i].cast("double") for i in range(dim)]
    ends = points.agg(*[f(c) for f in (F.min, F.max, F.avg) for c in part]).first()
    low, high, mean = ends[:dim], ends[dim : 2 * dim], ends[2 * dim :]
    if low[0] is None:
        return None
    norm = lambda terms: F.sqrt(sum((t * t for t in terms), F.lit(0.0)))
    to = lambda at: norm([c - F.lit(v) for c, v in zip(part, at)])
    middle, found = [(a + b) / 2 for a, b in zip(low, high)], 0.0
    at = middle
    for _ in range(4):
        far = points.agg(F.max(F.struct(to(at).alias("d"), "embedding")).alias("m")).first().m
        found = max(found, far.d) if at is not middle else found
        at = far.embedding
    corner = norm([F.greatest(c - F.lit(a), F.lit(b) - c) for c, a, b in zip(part, low, high)])
    reach = points.agg(F.max(to(middle)), F.max(to(mean))).first()
    least = F.lit(found * (1 - 1e-9))
    return aspect_ratio(points.where((corner >= least) & (to(middle) + F.lit(reach[0]) >= least) & (to(mean) + F.lit(reach[1]) >= least))).first().diameter


def spread(points: DataFrame, dim: int, shared) -> tuple[float | None, float | None, float | None]:
    """(diameter, smallest positive distance, median distance of a row to its nearest other) of different vectors; ``shared`` is what share_vectors made of them.

    Vectors of few components are searched in boxes, others block by block against all, where a task keeps a number a row.
    """
    spark, space = points.sparkSession, Metric()
    if dim <= FEW_COMPONENTS:
        near = exact.exact_knn_boxes(points, exact.as_queries(points), 1, skip_self=True).select("dist", F.lit(None).cast("double").alias("high"))
    else:

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            x, high = shared.value, 0.0
            every = np.arange(len(x))
            for batch in batches:
                for i in batch.column(0).to_numpy():
                    own = every[i : i + SPREAD_BLOCK]
                    _, d = space.nearest(x[own], x, every, 1, skip=own)
                    high, _ = space.extremes(x[own], x, high, 0.0)
                    d = d[np.isfinite(d)]
                    yield pa.RecordBatch.from_arrays([pa.array(d), pa.array(np.full(len(d), high))], ["dist", "high"])

        blocks = -(-len(shared.value) // SPREAD_BLOCK)
        near = spark.range(0, len(shared.value), SPREAD_BLOCK, max(1, min(blocks, 4 * spark.sparkContext.defaultParallelism))).mapInArrow(run, "dist double, high double")
    got = near.agg(F.min(F.when(F.col("dist") > 0, F.col("dist"))).alias("low"), F.median("dist").alias("median"), F.max("high").alias("high"), F.count_if(F.col("dist") == 0).alias("zero")).first()
    # Vectors whose difference has no square above zero hide their next distance.
    low = aspect_ratio(points).first().smallest if got.zero else got.low
    return diameter(points, dim) if dim <= FEW_COMPONENTS else got.high, low, got.median


def cover_size(x: np.ndarray, radius: float, space: Metric = Metric(), enough: int = 0) -> int:
    """How many balls of ``radius`` a greedy cover of the rows takes, in their order; any smaller number if it is at most ``enough``.

    Centres are found a few at a time by true distances; a matrix product in single precision then leaves out the
    rows that they cover, and rows within its error of the radius are measured.
    """
    if not len(x):
        return 0
    middle = x.mean(axis=0)
    centred = x - middle
    scale = float(np.einsum("ij,ij->i", centred, centred).max())
    unit = float(np.sqrt(scale)) if 0 < scale < np.inf else 1.0
    low = np.ascontiguousarray(centred / unit, np.float32)
    squares, live = np.einsum("ij,ij->i", low, low), np.arange(len(x))
    chord = 2 * np.sin(min(radius, np.pi) / 2) if space.name == "angular" else radius
    limit, slack, count = (chord / unit) ** 2, 16 * (x.shape[1] + 8) * 6e-8, 0
    while len(live) and count + len(live) > enough:
        head, new = live[:COVER_BLOCK], []
        while len(head):
            new.append(head[0])
            head = head[space.rows(x[head], x[head[0]]) > radius]
        count += len(new)
        live, low, squares = live[COVER_BLOCK:], low[COVER_BLOCK:], squares[COVER_BLOCK:]
        if not len(live):
            break
        if space.name == "l1":
            out = np.zeros(len(live), bool)
            for v in new:
                out |= space.rows(x[live], x[v]) <= radius
        else:
            own = np.ascontiguousarray((x[new] - middle) / unit, np.float32)
            least = (-2 * own) @ low.T
            least += np.einsum("ij,ij->i", own, own)[:, None]
            least = least.min(axis=0) + squares
            out = least <= limit - slack
            unsure = np.flatnonzero(~out & (least <= limit + slack))
            for i in range(0, len(unsure), 1024):
                some = unsure[i : i + 1024]
                out[some] = (space.cross(x[live[some]], x[new]) <= radius).any(axis=1)
        if out.any():
            live, low, squares = live[~out], low[~out], squares[~out]
    return count


def doubling_dimension(points: DataFrame, centres: int = 16, radii: int = 4, metric: str = "l2", shared=None) -> float:
    """log2 of the most half-radius balls a greedy cover of a ball needs, over sampled centres and radii.

    Only the centres are a sample, by a hash of the id; radii are quantiles of the distances to every row, and a ball
    holds every row within it. All vectors are broadcast (``shared``, if share_vectors made them already), and a task takes a centre.
    Wide balls go first: what cannot need more than the most so far is not covered to its end.
    """
    space = Metric(metric)
    shared = share_vectors(points, metric) if shared is None else shared

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x = shared.value
        for batch in batches:
            for c in batch.column(0).to_numpy():
                d, worst = space.rows(x, x[c]), 1
                for q in np.quantile(d[d > 0], np.linspace(0.2, 1, radii))[::-1] if (d > 0).any() else []:
                    worst = max(worst, cover_size(x[d <= q], q / 2, space, worst))
                yield pa.RecordBatch.from_arrays([pa.array([worst])], ["worst"])

    n = min(centres, len(shared.value))
    worst = points.sparkSession.range(0, n, 1, n).mapInArrow(run, "worst long").agg(F.max("worst")).first()[0] if n else None
    return float(np.log2(worst or 1))


def unit_scale(points: DataFrame, smallest: float) -> DataFrame:
    """Points scaled so that the least distance is 1; tau is then in these units."""
    return points.withColumn("embedding", F.transform(F.col("embedding").cast("array<double>"), lambda v: v / F.lit(smallest)))


def theory_regime(alpha: float, tau: float, scaled: bool, full: bool, capped: bool) -> bool:
    """Whether the analysis speaks about a graph: unit scale, tau at least 1, alpha over 1, all candidates, no cap."""
    return scaled and tau >= 1 and alpha > 1 and full and not capped


def ranked(df: DataFrame, by: str, order: str) -> DataFrame:
    return df.withColumn("rank", F.rank().over(W.partitionBy(by).orderBy(order)))
