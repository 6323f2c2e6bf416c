"""Search over indexes: sharded beam search, and the hop-synchronous form as joins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from annspark.functions import graphs as G
from annspark.functions.beam import beam_search as beam_kernel
from annspark.functions.beam import greedy_route as greedy_kernel
from annspark.functions.metric import Metric
from annspark.operators.build import Router, edges_of, lists_of, vectors_in_order
from annspark.operators.exact import to_matrix, top_k
from annspark.plans.session import ship_package, stage

FOUND = "q_id long, width int, vec_id long, dist double, ndc long, hops long, edges_scanned long"
COSTS = ("ndc", "hops", "edges_scanned")


def _graph_of(shard: pa.Table, metric: Metric) -> tuple[G.FlatGraph, np.ndarray, np.ndarray]:
    """(graph by place, ids, prepared vectors) of one shard's index rows."""
    level = shard.column("level").to_numpy()
    base = shard.filter(pa.array(level == 0)).sort_by("src")
    ids = base.column("src").to_numpy()
    x = metric.prepare(to_matrix(base.column("vec")))

    def adjacency(rows: pa.Table) -> np.ndarray:
        lists = rows.column("nbrs").combine_chunks()
        lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
        own, size = np.searchsorted(ids, rows.column("src").to_numpy()), np.diff(lists.offsets.to_numpy())
        out = np.full((len(ids), max(1, int(size.max(initial=0)))), -1, np.int32)
        row = np.repeat(np.arange(len(size)), size)
        out[own[row], np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)] = np.searchsorted(ids, lists.flatten().to_numpy(zero_copy_only=False))
        return out

    entry = int(np.flatnonzero(base.column("is_entry").to_numpy(zero_copy_only=False))[0])
    upper = [adjacency(shard.filter(pa.array(level == number))) for number in range(1, int(level.max(initial=0)) + 1)]
    return G.FlatGraph(entry, [adjacency(base), *upper]), ids, x


def route_queries(queries: DataFrame, router: Router | None, probes: int, tau: float = 0.0, radii: dict[int, float] | None = None) -> DataFrame:
    """(shard, q_id, qvec): each query with its nearest shards; with radii, also every shard its tau-ball can touch."""
    if router is None:
        return queries.select(F.lit(0).alias("shard"), F.col("q_id").cast("long"), F.col("qvec").cast("array<double>"))
    shared = queries.sparkSession.sparkContext.broadcast((router, radii))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r, reach = shared.value
        space = Metric(r.metric)
        for batch in batches:
            if not batch.num_rows:
                continue
            q = space.prepare(to_matrix(batch.column(1)))
            ids, _ = r.nearest(q, min(probes, len(r.centroids)))
            hit = np.zeros((len(q), len(r.centroids)), bool)
            hit[np.arange(len(q))[:, None], ids] = True
            if reach:
                hit |= space.cross(q, r.centroids) <= np.array([reach.get(s, -np.inf) for s in range(len(r.centroids))]) + tau
            row, shard = np.nonzero(hit)
            yield pa.RecordBatch.from_arrays([pa.array(shard.astype(np.int32)), batch.column(0).take(pa.array(row)), batch.column(1).take(pa.array(row))], ["shard", "q_id", "qvec"])

    return queries.select(F.col("q_id").cast("long"), F.col("qvec").cast("array<double>")).mapInArrow(run, "shard int, q_id long, qvec array<double>")


def shard_radii(index: DataFrame, router: Router) -> dict[int, float]:
    """The largest distance of a shard's point from its centroid: one number for each shard."""
    shared = index.sparkSession.sparkContext.broadcast(router)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r = shared.value
        space = Metric(r.metric)
        for batch in batches:
            if batch.num_rows:
                shard = batch.column(0).to_numpy()
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(space.rows(space.prepare(to_matrix(batch.column(1))), r.centroids[shard]))], ["shard", "d"])

    rows = index.where("level = 0").select("shard", "vec").mapInArrow(run, "shard int, d double")
    return {r.shard: r.d for r in rows.groupBy("shard").agg(F.max("d").alias("d")).collect()}


def search_indexes(
    index: DataFrame, settings: list[str], queries: DataFrame, k: int, widths: list[int], router: Router | None = None, probes: int = 1, metric: str = "l2",
    tau: float = 0.0, radii: dict[int, float] | None = None,
) -> DataFrame:
    """(setting, q_id, width, vec_id, dist, ndc, hops, edges_scanned): each query's k best for each setting and queue width, costs summed over shards.

    Queries travel to the shards of each setting's index.
    """
    if min(widths) < 1:
        raise ValueError("widths are positive")
    ship_package(index.sparkSession)
    space = Metric(metric)
    names = ["setting", "shard", *(c.split()[0] for c in FOUND.split(", "))]

    def run(shard: pa.Table, asked: pa.Table) -> pa.Table:
        out = []
        if asked.num_rows and shard.num_rows:
            g, ids, x = _graph_of(shard, space)
            q = space.prepare(to_matrix(asked.column("qvec")))
            q_ids, number, name = asked.column("q_id").to_numpy(), shard.column("shard")[0].as_py(), shard.column("setting")[0].as_py()
            for width in widths:
                got = G.search_layered(g, x, q, width, k, space)
                there = got.ids >= 0
                n = there.sum(axis=1)
                rep = lambda a: pa.array(np.repeat(a, n))
                same = lambda v, kind: pa.array([v] * int(n.sum()), kind)
                out.append(pa.Table.from_arrays(
                    [same(name, pa.string()), same(number, pa.int32()), rep(q_ids), same(width, pa.int32()), pa.array(ids[got.ids[there]]), pa.array(got.dist[there]), rep(got.ndc), rep(got.hops), rep(got.edges)],
                    names))
        kinds = [pa.string(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.int64()]
        return pa.concat_tables(out) if out else pa.schema(list(zip(names, kinds))).empty_table()

    asked = route_queries(queries, router, probes, tau, radii)
    asked = asked.withColumn("setting", F.explode(F.array(*map(F.lit, settings))))
    found = index.groupBy("setting", "shard").cogroup(asked.groupBy("setting", "shard")).applyInArrow(run, "setting string, shard int, " + FOUND)
    if router is None:
        return found.drop("shard")
    each = found.groupBy("setting", "q_id", "width", "shard").agg(*[F.max(c).alias(c) for c in COSTS])
    costs = each.groupBy("setting", "q_id", "width").agg(*[F.sum(c).alias(c) for c in COSTS])
    by = W.partitionBy("setting", "q_id", "width").orderBy("dist", "vec_id")
    once = found.select("setting", "q_id", "width", "vec_id", "dist").distinct()
    best = once.withColumn("_r", F.row_number().over(by)).where(F.col("_r") <= k).drop("_r")
    return best.join(costs, ["setting", "q_id", "width"]).select("setting", *names[2:])


def search_index(index: DataFrame, queries: DataFrame, k: int, widths: list[int], router: Router | None = None, probes: int = 1, metric: str = "l2", tau: float = 0.0, radii: dict[int, float] | None = None) -> DataFrame:
    """(q_id, width, vec_id, dist, ndc, hops, edges_scanned) of one index."""
    return search_indexes(index.withColumn("setting", F.lit("one")), ["one"], queries, k, widths, router, probes, metric, tau, radii).drop("setting")


def greedy_routes(points: DataFrame, edges: DataFrame, queries: DataFrame, entry: int, metric: str = "l2") -> DataFrame:
    """(q_id, hop, vec_id, dist): the vertices that greedy routing visits, the last being its answer. The whole graph is broadcast, unless it comes as lists."""
    if "nbrs" in edges.columns:
        return greedy_routes_joined(points, edges, queries, entry, metric)
    spark = points.sparkSession
    ship_package(spark)
    space = Metric(metric)
    rows = points.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>")).orderBy("vec_id").toArrow()
    ids = rows.column(0).to_numpy()
    lists = edges.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("n")).toArrow()
    neighbors: list[list[int]] = [[] for _ in ids]
    for src, row in zip(lists.column(0).to_pylist(), lists.column(1).to_pylist()):
        neighbors[int(np.searchsorted(ids, src))] = np.searchsorted(ids, row).tolist()
    from annspark.functions.beam import padded

    shared = spark.sparkContext.broadcast((ids, space.prepare(to_matrix(rows.column(1))), padded(neighbors)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x, adjacency = shared.value
        at = int(np.searchsorted(ids, entry))
        for batch in batches:
            if not batch.num_rows:
                continue
            got = greedy_kernel(adjacency, x, space.prepare(to_matrix(batch.column(1))), at, space)
            n = [len(t) for t in got.traces]
            steps = [s for t in got.traces for s in t]
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.repeat(batch.column(0).to_numpy(), n)), pa.array(np.concatenate([np.arange(m) for m in n]).astype(np.int32)), pa.array(ids[[s[0] for s in steps]]), pa.array([s[1] for s in steps])],
                ["q_id", "hop", "vec_id", "dist"],
            )

    return queries.select(F.col("q_id").cast("long"), F.col("qvec").cast("array<double>")).mapInArrow(run, "q_id long, hop int, vec_id long, dist double")


def greedy_routes_joined(points: DataFrame, edges: DataFrame, queries: DataFrame, entry: int, metric: str = "l2", rounds: int = 1000) -> DataFrame:
    """The routes that greedy_routes takes, of a graph that is neither collected nor broadcast.

    Each round brings the rows of the vertices where routes stand to these, which move along them; vectors are broadcast.
    """
    spark = points.sparkSession
    ship_package(spark)
    space = Metric(metric)
    ids, _, x = vectors_in_order(points, space)
    at = int(np.searchsorted(ids, entry))
    shared = spark.sparkContext.broadcast((ids, x))
    lists = lists_of(edges).select("src", "nbrs")
    names = ["q_id", "qvec", "hop", "vec_id", "dist"]
    kind = "q_id long, qvec array<double>, hop int, vec_id long, dist double"

    def start(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x = shared.value
        for batch in batches:
            if batch.num_rows:
                d = space.rows(space.prepare(to_matrix(batch.column(1))), x[at])
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.zeros(batch.num_rows, np.int32)), pa.array(np.full(batch.num_rows, ids[at])), pa.array(d)], names)

    def move(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Of each vertex first its row of neighbours, then the routes that stand there."""
        ids, x = shared.value
        now, near = None, np.empty(0, np.int64)
        for batch in batches:
            if not batch.num_rows:
                continue
            vertex, is_route = batch.column(3).to_numpy(), batch.column(5).is_null().to_numpy(zero_copy_only=False)
            cuts = np.flatnonzero(np.concatenate([[True], (vertex[1:] != vertex[:-1]) | (is_route[1:] != is_route[:-1]) | ~is_route[1:], [True]]))
            for s, e in zip(cuts, cuts[1:]):
                if vertex[s] != now:
                    now, near = vertex[s], np.empty(0, np.int64)
                if not is_route[s]:
                    near = np.sort(np.searchsorted(ids, batch.column(5)[s].values.to_numpy()))
                    continue
                part = batch.slice(s, e - s)
                q, dist = space.prepare(to_matrix(part.column(1))), part.column(4).to_numpy()
                if not len(near):
                    continue
                best, d = np.empty(len(q), np.int64), np.empty(len(q))
                block = max(1, 500_000 // len(near))
                for i in range(0, len(q), block):
                    every = space.cross(q[i : i + block], x[near])
                    best[i : i + block], d[i : i + block] = every.argmin(axis=1), every.min(axis=1)
                goes = d < dist
                part = part.filter(pa.array(goes))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array((part.column(2).to_numpy() + 1).astype(np.int32)), pa.array(ids[near[best[goes]]]), pa.array(d[goes])], names)

    tasks = 4 * spark.sparkContext.defaultParallelism
    front = stage(queries.select(F.col("q_id").cast("long"), F.col("qvec").cast("array<double>")).mapInArrow(start, kind), "routes")
    steps = [front]
    for _ in range(rounds):
        if not front.take(1):
            out = steps[0]
            for step in steps[1:]:
                out = out.unionByName(step)
            return out.drop("qvec")
        blank = [F.lit(None).cast(t).alias(n) for n, t in (("q_id", "long"), ("qvec", "array<double>"), ("hop", "int"))]
        rows = lists.join(front.select(F.col("vec_id").alias("src")).distinct(), "src", "left_semi").select(*blank, F.col("src").alias("vec_id"), F.lit(None).cast("double").alias("dist"), "nbrs")
        met = rows.unionByName(front.withColumn("nbrs", F.lit(None).cast("array<long>"))).repartition(tasks, "vec_id").sortWithinPartitions("vec_id", F.col("nbrs").isNull())
        front = stage(met.mapInArrow(move, kind), "routes")
        steps.append(front)
    raise RuntimeError("the routes are longer than the round limit")


def greedy_routes_full(points: DataFrame, rule, queries: DataFrame, entry: int, metric: str = "l2", rounds: int = 1000) -> DataFrame:
    """The routes that greedy_routes takes over the full graph of ``rule``, of which only the visited rows are made.

    A vertex's row depends on no other row. So each round makes the rows of the vertices where routes stand, each
    once, and moves the routes along them; no graph is collected or broadcast, only all vectors.
    """
    spark = points.sparkSession
    ship_package(spark)
    space = Metric(metric)
    ids, _, x = vectors_in_order(points, space)
    at = int(np.searchsorted(ids, entry))
    shared = spark.sparkContext.broadcast((ids, x))

    def start(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x = shared.value
        for batch in batches:
            if batch.num_rows:
                d = space.rows(space.prepare(to_matrix(batch.column(1))), x[at])
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.zeros(batch.num_rows, np.int32)), pa.array(np.full(batch.num_rows, ids[at])), pa.array(d)], names)

    def move(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come grouped by vertex: its edges are made once for all routes that stand there."""
        ids, x = shared.value
        full, now, near = None, None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            full = full or G.FullRows(x, rule, space)
            q, own, dist = space.prepare(to_matrix(batch.column(1))), np.searchsorted(ids, batch.column(3).to_numpy()), batch.column(4).to_numpy()
            goes, to, to_d = np.zeros(len(own), bool), np.zeros(len(own), np.int64), np.zeros(len(own))
            for i, v in enumerate(own.tolist()):
                if v != now:
                    now, (near, _) = v, next(full.rows(np.array([v])))
                if len(near):
                    near = np.sort(near)
                    d = space.rows(x[near], q[i])
                    best = int(d.argmin())
                    goes[i], to[i], to_d[i] = d[best] < dist[i], ids[near[best]], d[best]
            part = batch.filter(pa.array(goes))
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array((part.column(2).to_numpy() + 1).astype(np.int32)), pa.array(to[goes]), pa.array(to_d[goes])], names)

    names = ["q_id", "qvec", "hop", "vec_id", "dist"]
    kind = "q_id long, qvec array<double>, hop int, vec_id long, dist double"
    tasks = 4 * spark.sparkContext.defaultParallelism
    front = stage(queries.select(F.col("q_id").cast("long"), F.col("qvec").cast("array<double>")).mapInArrow(start, kind), "routes")
    steps = [front]
    for _ in range(rounds):
        if not front.take(1):
            out = steps[0]
            for step in steps[1:]:
                out = out.unionByName(step)
            return out.drop("qvec")
        placed = front.repartition(tasks, "vec_id").sortWithinPartitions("vec_id")
        front = stage(placed.mapInArrow(move, kind), "routes")
        steps.append(front)
    raise RuntimeError("the routes are longer than the round limit")


def bsp_search(index: DataFrame, queries: DataFrame, k: int, width: int, expand: int = 1, rounds: int = 10_000) -> DataFrame:
    """(q_id, rank, vec_id, dist, ndc, hops): beam search as one superstep of joins for each hop.

    It works on a graph across shards (base layer, Euclidean). Each step expands
    the ``expand`` nearest open entries of every live query; with one it equals
    the kernel. Hops are supersteps here, so fewer hops are fewer shuffles.
    """
    spark = index.sparkSession
    base = index.where("level = 0")
    links = stage(base.select("src", F.explode("nbrs").alias("dst")), "bsp-links")
    vectors = stage(base.select(F.col("src").alias("id"), F.col("vec").alias("e")), "bsp-vectors")
    entry = base.where("is_entry").agg(F.min("src")).first()[0]
    away = F.sqrt(F.aggregate(F.zip_with("qvec", "e", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, z: s + z))
    asked = stage(queries.select(F.col("q_id").cast("long"), F.col("qvec").cast("array<double>")), "bsp-queries")
    first = asked.join(F.broadcast(vectors.where(F.col("id") == entry)), how="inner", on=F.lit(True)) if entry is not None else None
    if first is None:
        return spark.createDataFrame([], "q_id long, rank int, vec_id long, dist double, ndc long, hops long")
    pool = stage(first.select("q_id", "id", away.alias("dist"), F.lit(False).alias("open_done"), F.lit(0).alias("step")), "bsp-pool")
    by = W.partitionBy("q_id").orderBy("dist", "id")
    for step in range(1, rounds + 1):
        queue = pool.withColumn("_r", F.row_number().over(by)).where(F.col("_r") <= width)
        pick = queue.where(~F.col("open_done")).withColumn("_o", F.row_number().over(by)).where(F.col("_o") <= expand).select("q_id", "id")
        pick = stage(pick, "bsp-pick")
        if not pick.take(1):
            break
        seen = pool.select("q_id", "id")
        near = pick.join(links, F.col("id") == F.col("src")).select("q_id", F.col("dst").alias("id")).distinct().join(seen, ["q_id", "id"], "left_anti")
        new = near.join(asked, "q_id").join(vectors, "id").select("q_id", "id", away.alias("dist"), F.lit(False).alias("open_done"), F.lit(step).alias("step"))
        marked = pool.join(pick.withColumn("_x", F.lit(True)), ["q_id", "id"], "left").select("q_id", "id", "dist", (F.col("open_done") | F.coalesce("_x", F.lit(False))).alias("open_done"), "step")
        pool = stage(marked.unionByName(new), "bsp-pool")
    costs = pool.groupBy("q_id").agg(F.count("*").alias("ndc"), F.count_if("open_done").alias("hops"))
    best = top_k(pool.select("q_id", F.col("id").alias("vec_id"), "dist"), k)
    return best.join(costs, "q_id")


def lsh_knn(base: DataFrame, queries: DataFrame, k: int, bucket: float = 1.0, tables: int = 8, seed: int = 11) -> DataFrame:
    """(q_id, rank, vec_id, dist) through Spark ML's bucketed random projections: an older family for comparison."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    vec = lambda df, i, e: df.select(F.col(i).alias("id"), array_to_vector(F.col(e).cast("array<double>")).alias("v"))
    a, b = vec(queries, "q_id", "qvec"), vec(base, "vec_id", "embedding")
    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=bucket, numHashTables=tables, seed=seed).fit(b)
    near = model.approxSimilarityJoin(a, b, float("inf"), "dist").select(F.col("datasetA.id").alias("q_id"), F.col("datasetB.id").alias("vec_id"), "dist")
    return top_k(near, k)


def cell_knn(points: DataFrame, queries: DataFrame, k: int, router: Router, probes: int, metric: str = "l2") -> DataFrame:
    """(q_id, rank, vec_id, dist) by scanning the nearest cells: the inverted-file family for comparison."""
    from annspark.operators.build import assign_shards

    space = Metric(metric)
    ship_package(points.sparkSession)

    def run(cell: pa.Table, asked: pa.Table) -> pa.Table:
        kind = pa.schema([("q_id", pa.int64()), ("vec_id", pa.int64()), ("dist", pa.float64())])
        if not cell.num_rows or not asked.num_rows:
            return kind.empty_table()
        ids, d = space.nearest(space.prepare(to_matrix(asked.column("qvec"))), space.prepare(to_matrix(cell.column("embedding"))), cell.column("vec_id").to_numpy(), k)
        there = np.isfinite(d)
        return pa.Table.from_arrays([pa.array(np.repeat(asked.column("q_id").to_numpy(), there.sum(axis=1))), pa.array(ids[there]), pa.array(d[there])], schema=kind)

    cells = assign_shards(points, router).groupBy("shard")
    found = cells.cogroup(route_queries(queries, router, probes).groupBy("shard")).applyInArrow(run, "q_id long, vec_id long, dist double")
    return top_k(found, k)


__all__ = ["beam_kernel", "bsp_search", "cell_knn", "edges_of", "greedy_routes", "lsh_knn", "route_queries", "search_index", "shard_radii"]
