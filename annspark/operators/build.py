"""Graph construction on Spark: full-candidate graphs, and sharded local graphs.

Local graphs are built a shard at a time: points get a shard from a router of
centroids (in two levels if there are many), and each shard, about as large as
one machine handles well, is one group of an Arrow function. Several methods or
settings are built together, each shard of each being a group. An index row is a
vertex: its vector, out-neighbours and build log, so search and measures need no
further join.
"""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from annspark.functions import graphs as G
from annspark.functions.metric import Metric
from annspark.functions.rules import Rule
from annspark.functions.select import fold_sql
from annspark.operators.exact import to_matrix
from annspark.plans.session import ship_package, stage

EDGES = "src long, dst long, dist double, rank int"
LISTS, LIST_NAMES = "src long, nbrs array<long>, dists array<double>", ["src", "nbrs", "dists"]
INDEX = (
    "shard int, src long, vec array<double>, nbrs array<long>, dists array<double>, level int, is_entry boolean, n_repair int, "
    "alpha_used double, steps int, pairs long, distinct_kept int, selections long, build_s double"
)
#: Sources of one task of a full graph, at most about so many.
SOURCE_BLOCK = 1024


def vectors_in_order(points: DataFrame, space: Metric) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids in order, raw vectors, prepared ones) of all points, for a broadcast."""
    rows = points.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>")).orderBy("vec_id").toArrow()
    raw = to_matrix(rows.column(1))
    return rows.column(0).to_numpy(), raw, space.prepare(raw) if len(raw) else raw


def _sources(points: DataFrame, n: int) -> DataFrame:
    """Ids in blocks of a bounded size, at least a few for each core."""
    tasks = max(1, min(n, max(4 * points.sparkSession.sparkContext.defaultParallelism, -(-n // SOURCE_BLOCK))))
    return points.select(F.col("vec_id").cast("long")).repartition(tasks)


def full_graph(points: DataFrame, rule: Rule, metric: str = "l2", limit: int | None = None, cap: int | None = None, lists: bool = False) -> DataFrame:
    """(src, dst, dist, rank): the rule's kept set of every point over all others, with ``cap`` the nearest so many of it.

    With ``lists`` a row has all of a point's, nearest first: (src, nbrs, dists). It looks at every pair of points and broadcasts all vectors; a caller who wants no quadratic job sets ``limit``.
    """
    spark = points.sparkSession
    ship_package(spark)
    n = points.count()
    if limit is not None and n > limit:
        raise ValueError(f"{n} points; a full-candidate graph is quadratic and limited to {limit}")
    space = Metric(metric)
    ids, _, x = vectors_in_order(points, space)
    shared = spark.sparkContext.broadcast((ids, x))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x = shared.value
        full = None
        for batch in batches:
            if not batch.num_rows:
                continue
            full = full or G.FullRows(x, rule, space)
            own = np.searchsorted(ids, batch.column(0).to_numpy())
            for i in range(0, len(own), 64):
                part = own[i : i + 64]
                rows = list(full.rows(part, cap))
                size = [len(kept) for kept, _ in rows]
                if lists:
                    ends = pa.array(np.cumsum([0, *size]).astype(np.int32))
                    flat = (ids[np.concatenate([kept for kept, _ in rows])], np.concatenate([d for _, d in rows]))
                    yield pa.RecordBatch.from_arrays([pa.array(ids[part]), *[pa.ListArray.from_arrays(ends, pa.array(a)) for a in flat]], LIST_NAMES)
                    continue
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.repeat(ids[part], size)), pa.array(ids[np.concatenate([kept for kept, _ in rows])]), pa.array(np.concatenate([d for _, d in rows]), pa.float64()),
                        pa.array(np.concatenate([np.arange(1, m + 1, dtype=np.int32) for m in size])),
                    ],
                    ["src", "dst", "dist", "rank"],
                )

    return _sources(points, n).mapInArrow(run, LISTS if lists else EDGES)


def lists_of(edges: DataFrame) -> DataFrame:
    """(src, nbrs, dists) of edges, or of what full_graph gave as lists already."""
    if "nbrs" in edges.columns:
        return edges.select(*LIST_NAMES)
    rows = edges.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dist", "dst"))).alias("n"))
    return rows.select("src", F.col("n.dst").alias("nbrs"), F.col("n.dist").alias("dists"))


def full_graph_sql(points: DataFrame, rule: Rule, limit: int | None = None) -> DataFrame:
    """The same by built-in functions alone, for small sets and for reading."""
    if limit is not None and (n := points.count()) > limit:
        raise ValueError(f"{n} points; the form in SQL is limited to {limit}")
    p = points.select(F.col("vec_id").alias("p"), F.col("embedding").cast("array<double>").alias("pe"))
    u = points.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("e"))
    diff = F.zip_with("pe", "e", lambda a, b: (a - b) * (a - b))
    pairs = p.join(F.broadcast(u), F.col("p") != F.col("id")).withColumn("d", F.sqrt(F.aggregate(diff, F.lit(0.0), lambda s, z: s + z)))
    cands = pairs.groupBy("p").agg(F.collect_list(F.struct("d", "id", "e")).alias("c"))
    kept = cands.select("p", F.posexplode(F.expr(fold_sql("c", rule))).alias("at", "k"))
    return kept.select(F.col("p").alias("src"), F.col("k.id").alias("dst"), F.col("k.d").alias("dist"), (F.col("at") + 1).cast("int").alias("rank"))


# -- shards ------------------------------------------------------------------

#: Points of one shard, about so many at most.
SHARD_POINTS = 1_000_000
#: A router with more centroids than this looks through its nearest groups of centroids only.
FLAT_ROUTER, GROUPS_LOOKED = 1024, 8


def _halves(x: np.ndarray, rounds: int = 8) -> np.ndarray:
    """Which of two means each row is nearer to."""
    far = x[np.argmax(((x - x.mean(axis=0)) ** 2).sum(axis=1))]
    c = np.stack([far, x[np.argmax(((x - far) ** 2).sum(axis=1))]])
    side = np.zeros(len(x), bool)
    for _ in range(rounds):
        side = ((x - c[1]) ** 2).sum(axis=1) < ((x - c[0]) ** 2).sum(axis=1)
        if side.all() or not side.any():
            break
        c = np.stack([x[~side].mean(axis=0), x[side].mean(axis=0)])
    return side


def _leaves(x: np.ndarray, count: int) -> list[np.ndarray]:
    """``count`` clusters of rows (places), the largest one being halved each time, so that none stays far above the others."""
    leaves = [(-len(x), 0, np.arange(len(x)))]
    for number in range(1, count):
        size, _, own = heapq.heappop(leaves)
        side = _halves(x[own])
        if size == -1 or side.all() or not side.any():
            raise ValueError(f"{count} shards of {len(leaves) + 1} different places in the sample")
        for part in (own[~side], own[side]):
            heapq.heappush(leaves, (-len(part), 2 * number + len(leaves), part))
    return [own for *_, own in sorted(leaves, key=lambda leaf: int(leaf[2][0]))]


@dataclass(frozen=True)
class Router:
    """Centroids of shards; its size is the number of shards, not of points."""

    centroids: np.ndarray
    metric: str = "l2"

    @cached_property
    def groups(self) -> tuple[np.ndarray, list[np.ndarray]]:
        """(centres, members): centroids in about as many groups as the root of their number."""
        members = _leaves(self.centroids, int(len(self.centroids) ** 0.5))
        return np.stack([self.centroids[m].mean(axis=0) for m in members]), members

    def nearest(self, x: np.ndarray, probes: int) -> tuple[np.ndarray, np.ndarray]:
        space = Metric(self.metric)
        if len(self.centroids) <= FLAT_ROUTER:
            return space.nearest(x, self.centroids, np.arange(len(self.centroids)), probes)
        centres, members = self.groups
        looked, _ = space.nearest(x, centres, np.arange(len(centres)), min(GROUPS_LOOKED, len(centres)))
        best_i, best_d = np.full((len(x), probes), -1, np.int64), np.full((len(x), probes), np.inf)
        for g, own in enumerate(members):
            rows = np.flatnonzero((looked == g).any(axis=1))
            if len(rows):
                ids, d = space.nearest(x[rows], self.centroids[own], own, probes)
                ids, d = np.concatenate([best_i[rows], ids], axis=1), np.concatenate([best_d[rows], d], axis=1)
                order = np.lexsort((ids, d), axis=1)[:, :probes]
                best_i[rows], best_d[rows] = np.take_along_axis(ids, order, 1), np.take_along_axis(d, order, 1)
        return best_i, best_d


def train_router(points: DataFrame, shards: int, metric: str = "l2", sample: int = 20_000, seed: int = 3) -> Router:
    """Centroids from a bounded sample of points, chosen by a hash of the id: clusters are halved, the largest first.

    The sample has at least 32 points a shard; too few different points for so many shards are an error.
    """
    n = points.count()
    rate = min(1.0, max(sample, 32 * shards) / max(1, n))
    chosen = points.where(F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(1_000_000)) < int(rate * 1_000_000) + (rate >= 1)).select("vec_id", F.col("embedding").cast("array<double>"))
    rows = chosen.orderBy(F.xxhash64("vec_id", F.lit(seed + 1)), "vec_id").toArrow()
    space = Metric(metric)
    x = space.prepare(to_matrix(rows.column(1)))
    c = np.stack([x[own].mean(axis=0) for own in _leaves(x, shards)])
    return Router(space.prepare(c) if metric in ("chord", "angular") else c, metric)


def router_for(points: DataFrame, shard_points: int = SHARD_POINTS, metric: str = "l2") -> Router | None:
    """A router to shards of about ``shard_points``; none if all points fit one."""
    n = points.count()
    return train_router(points, -(-n // shard_points), metric) if n > shard_points else None


def assign_shards(points: DataFrame, router: Router, rho: float = 0.0) -> DataFrame:
    """Rows with a shard; points whose second centroid is within (1 + rho) of the first are in both shards."""
    ship_package(points.sparkSession)
    shared = points.sparkSession.sparkContext.broadcast(router)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r = shared.value
        space = Metric(r.metric)
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, d = r.nearest(space.prepare(to_matrix(batch.column(1))), 2 if rho > 0 else 1)
            row, shard = np.arange(len(ids)), ids[:, 0]
            if rho > 0 and ids.shape[1] > 1:
                both = np.flatnonzero(d[:, 1] <= (1 + rho) * d[:, 0])
                row, shard = np.concatenate([row, both]), np.concatenate([shard, ids[both, 1]])
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row)), batch.column(1).take(pa.array(row)), pa.array(shard.astype(np.int32))], ["vec_id", "embedding", "shard"])

    return points.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>")).mapInArrow(run, "vec_id long, embedding array<double>, shard int")


def _index_table(g: G.Graph, ids: np.ndarray, raw: np.ndarray, shard: int, seconds: float, own: np.ndarray | None = None) -> pa.Table:
    """A graph's index rows, from flat arrays; ``own`` has the places of the rows if they are a part of all."""
    n, dim = raw.shape

    def lists(rows: list, kind: pa.DataType, values=None) -> pa.Array:
        ends = np.cumsum([0, *map(len, rows)]).astype(np.int32)
        flat = np.concatenate([np.asarray(r) for r in rows]) if ends[-1] else np.empty(0)
        return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat.astype(np.int64) if kind == pa.int64() else flat.astype(np.float64), kind) if values is None else pa.array(values[flat.astype(np.int64)], kind))

    logs = {f: [getattr(e, f) for e in g.log] if g.log else [None] * n for f in ("alpha_used", "steps", "pairs", "distinct")}
    base = [
        pa.array(np.full(n, shard, np.int32)), pa.array(ids if own is None else ids[own]), pa.ListArray.from_arrays(pa.array(np.arange(0, n * dim + 1, dim, dtype=np.int32)) if dim else pa.array(np.zeros(n + 1, np.int32)), pa.array(raw.ravel())),
        lists(g.neighbors, pa.int64(), ids), lists(g.dists, pa.float64()), pa.array(np.zeros(n, np.int32)), pa.array(np.arange(n) == g.entry),
        pa.array(np.bincount([u for u, _ in g.repairs], minlength=n).astype(np.int32)), pa.array(logs["alpha_used"], pa.float64()), pa.array(logs["steps"], pa.int32()),
        pa.array(logs["pairs"], pa.int64()), pa.array(logs["distinct"], pa.int32()), pa.array(np.full(n, g.selections)), pa.array(np.full(n, seconds)),
    ]
    names = [c.split()[0] for c in INDEX.split(", ")]
    out = [pa.Table.from_arrays(base, names)]
    for level, layer in enumerate(g.layers, 1):
        own = np.fromiter(layer, np.int64, len(layer))
        m = len(own)
        part = {"shard": pa.array(np.full(m, shard, np.int32)), "src": pa.array(ids[own]), "nbrs": lists(list(layer.values()), pa.int64(), ids), "level": pa.array(np.full(m, level, np.int32)), "is_entry": pa.array(own == g.entry), "n_repair": pa.array(np.zeros(m, np.int32))}
        out.append(pa.Table.from_arrays([part[c] if c in part else pa.nulls(m, base[i].type) for i, c in enumerate(names)], names))
    return pa.concat_tables(out)


def _full_indexes(points: DataFrame, settings: dict[str, tuple[str, G.Params]], space: Metric) -> DataFrame:
    """Index rows of full-candidate graphs over one shard: a vertex's row depends on no other, so vertices are spread over tasks.

    build_s is each vertex's own share of its block's CPU seconds.
    """
    ids, raw, x = vectors_in_order(points, space)
    entry = G.exact_entry(x, space) if len(ids) > 1 else 0
    rules = {name: G.full_rule(method, params) for name, (method, params) in settings.items()}
    shared = points.sparkSession.sparkContext.broadcast((ids, raw, x))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, raw, x = shared.value
        for batch in batches:
            own = np.searchsorted(ids, batch.column(0).to_numpy())
            for name, rule in rules.items():
                full = G.FullRows(x, rule, space) if len(own) else None
                for i in range(0, len(own), 64):
                    part, began = own[i : i + 64], time.process_time()
                    rows = list(full.rows(part))
                    share = (time.process_time() - began) / len(part)
                    g = G.Graph([kept for kept, _ in rows], [d for _, d in rows], -1, [], len(ids))
                    table = _index_table(g, ids, raw[part], 0, share, part)
                    table = table.set_column(table.schema.get_field_index("is_entry"), "is_entry", pa.array(part == entry))
                    yield from table.add_column(0, "setting", pa.array([name] * len(part), pa.string())).combine_chunks().to_batches()

    return _sources(points, len(ids)).mapInArrow(run, "setting string, " + INDEX)


def build_indexes(points: DataFrame, settings: dict[str, tuple[str, G.Params]], router: Router | None = None, metric: str = "l2", rho: float = 0.0) -> DataFrame:
    """Index rows of each (method, params) of ``settings``, under its name in the column `setting`.

    Each shard of each setting is a group of its own, so settings are built side
    by side, but where that leaves enough for all tasks, settings that share K-NN graph and candidates are one group; full-candidate graphs of one shard are built a vertex at a time in many tasks. Without a router all points are one shard, and more than a shard's
    points are an error. Ids must be distinct; collapse_duplicates makes vectors
    distinct too.
    """
    for method, _ in settings.values():
        if method not in G.METHODS:
            raise ValueError(f"unknown method {method}")
    ship_package(points.sparkSession)
    if router is None and (n := points.count()) > SHARD_POINTS:
        raise ValueError(f"{n} points in one shard; use router_for")
    space = Metric(metric)
    apart = {name: s for name, s in settings.items() if s[0] in G.FULL} if router is None else {}
    if apart:
        full = _full_indexes(points, apart, space)
        rest = {name: s for name, s in settings.items() if name not in apart}
        return build_indexes(points, rest, router, metric, rho).unionByName(full) if rest else full
    placed = assign_shards(points, router, rho) if router is not None else points.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>"), F.lit(0).alias("shard"))
    families = _families(settings, len(router.centroids) if router is not None else 1, points.sparkSession.sparkContext.defaultParallelism)

    def run(group: pa.Table) -> pa.Table:
        ids = group.column("vec_id").to_numpy()
        order = np.argsort(ids, kind="stable")
        ids = ids[order]
        raw = to_matrix(group.column("embedding"))[order]
        x, shard, names, out = space.prepare(raw), group.column("shard")[0].as_py(), families[group.column("family")[0].as_py()], []
        began, prepared = time.process_time(), None
        if len(names) > 1 and len(x) > 1:
            prepared = G.prepare_local(x, settings[names[0]][1], space)
        before = time.process_time() - began
        for name in names:
            method, params = settings[name]
            began = time.process_time()
            g = G.build(method, x, params, space, prepared)
            table = _index_table(g, ids, raw, shard, before + time.process_time() - began)
            out.append(table.add_column(0, "setting", pa.array([name] * table.num_rows, pa.string())))
        return pa.concat_tables(out)

    groups = [(f, s) for f in range(len(families)) for s in range(len(router.centroids) if router is not None else 1)]
    places = F.broadcast(_slots(points.sparkSession, groups))
    placed = placed.join(places, "shard").repartition(len(groups), "slot")
    return placed.groupBy("slot").applyInArrow(run, "setting string, " + INDEX)


def _families(settings: dict[str, tuple[str, G.Params]], shards: int, tasks: int) -> list[list[str]]:
    """Settings that one task builds for a shard: those that share K-NN graph and candidates, if that leaves enough for all tasks; most work first."""
    by: dict[tuple, list[str]] = {}
    for name, (method, params) in settings.items():
        shared = G.prepared_by(method, params)
        by.setdefault((name,) if shared is None else shared, []).append(name)
    if len(by) * shards < tasks:
        return [[name] for name in settings]
    return sorted(by.values(), key=lambda names: -len(names))


def _slots(spark: SparkSession, groups: list[tuple[int, int]]) -> DataFrame:
    """(family, shard, slot): numbers whose hashes put each group in a partition of its own, so that none waits for another in its task."""
    n = len(groups)
    drawn = spark.range(n * (n.bit_length() + 8)).select(F.col("id").cast("int").alias("slot"))
    drawn = drawn.groupBy(F.pmod(F.hash("slot"), F.lit(n)).alias("at")).agg(F.min("slot").alias("slot"))
    at = {r["at"]: r["slot"] for r in drawn.collect()}
    # Where no number was drawn for a partition, a negative one shares another's.
    return spark.createDataFrame([(f, s, at.get(i, -1 - i)) for i, (f, s) in enumerate(groups)], "family int, shard int, slot int")


def build_swept(points: DataFrame, settings: dict[str, tuple[str, G.Params]], metric: str = "l2") -> DataFrame:
    """Index rows as of build_indexes, of settings of local methods over one shard that differ in selection alone.

    They share the K-NN graph, which is exact for any number of points, and the candidates. Neighbours, candidates and
    forward edges of a vertex need no other vertex's, so they are made in many tasks, and only backward edges and repair
    are a task a setting. Vectors and the K-NN graph (4 bytes an edge) are broadcast.
    """
    spark = points.sparkSession
    ship_package(spark)
    space = Metric(metric)
    first = next(iter(settings.values()))[1]
    for method, p in settings.values():
        if method not in G.LOCAL or G.prepared_by(method, p) != G.prepared_by(method, first):
            raise ValueError("settings of a sweep share K-NN graph and candidates")
    ids, raw, x = vectors_in_order(points, space)
    n = len(ids)
    if n < 2:
        return build_indexes(points, settings, None, metric)
    if n > SHARD_POINTS:
        raise ValueError(f"{n} points in one shard; use router_for")
    k = min(first.K, n - 1)
    shared = spark.sparkContext.broadcast((ids, raw, x))

    def lists(a: np.ndarray) -> pa.Array:
        return pa.ListArray.from_arrays(pa.array(np.arange(0, a.size + 1, a.shape[1], dtype=np.int32)), pa.array(a.ravel()))

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, _, x = shared.value
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part, began = batch.slice(i, 256).column(0), time.process_time()
                own = np.searchsorted(ids, part.to_numpy())
                got, d = space.nearest(x[own], x, np.arange(len(x)), k, skip=own)
                yield pa.RecordBatch.from_arrays([part, lists(got.astype(np.int32)), lists(d), pa.array(np.full(len(own), (time.process_time() - began) / len(own)))], ["src", "nbrs", "dists", "s"])

    graph = stage(_sources(points, n).mapInArrow(near, "src long, nbrs array<int>, dists array<double>, s double"), "sweep-knn")
    knn = graph.select("src", "nbrs").orderBy("src").toArrow().column(1).combine_chunks().flatten().to_numpy().reshape(n, k)
    entry = G.find_entry(x, knn, first.L, space, first.seed, first.start)
    adjacency = spark.sparkContext.broadcast(knn)
    forward_names = ["setting", "src", "nbrs", "dists", "alpha_used", "steps", "pairs", "distinct", "s"]

    def forward(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, _, x = shared.value
        knn = adjacency.value
        selects = {name: G.make_select_many(G.LOCAL[method][0], x, p, space) for name, (method, p) in settings.items()}
        for batch in batches:
            for i in range(0, batch.num_rows, 64):
                part, began = batch.slice(i, 64), time.process_time()
                own = np.searchsorted(ids, part.column(0).to_numpy())
                pools = G.local_candidates(x, knn, to_matrix(part.column(2)), entry, first, space, own)
                before = part.column(3).to_numpy() + (time.process_time() - began) / len(own)
                for name, select in selects.items():
                    began = time.process_time()
                    got = select([c for c, _ in pools], [d for _, d in pools])
                    took = before + (time.process_time() - began) / len(own)
                    yield pa.RecordBatch.from_arrays([
                        pa.array([name] * len(own)), part.column(0), pa.array([c[g.kept] for (c, _), g in zip(pools, got)], pa.list_(pa.int64())), pa.array([d[g.kept] for (_, d), g in zip(pools, got)], pa.list_(pa.float64())),
                        pa.array([g.alpha_used for g in got], pa.float64()), *[pa.array([getattr(g, f) for g in got], pa.int64()) for f in ("steps", "pairs", "distinct")], pa.array(took),
                    ], forward_names)

    def finish(rows: pa.Table) -> pa.Table:
        ids, raw, x = shared.value
        rows, began = rows.sort_by("src"), time.process_time()
        name = rows.column("setting")[0].as_py()
        method, p = settings[name]
        logs = [rows.column(f).to_pylist() for f in ("alpha_used", "steps", "pairs", "distinct")]
        g = G.Graph(rows.column("nbrs").to_pylist(), rows.column("dists").to_pylist(), entry, [G.Selection([], *e) for e in zip(*logs)])
        policy, way = G.LOCAL[method]
        G.finish_local(x, g, G.make_select(policy, p, space), p, p.backward or way, space, G.make_select_many(policy, x, p, space), None if policy == "adaptive" else G.make_rule(policy, p))
        table = _index_table(g, ids, raw, 0, float(rows.column("s").to_numpy().sum()) + time.process_time() - began)
        return table.add_column(0, "setting", pa.array([name] * table.num_rows, pa.string()))

    edges = graph.mapInArrow(forward, "setting string, src long, nbrs array<long>, dists array<double>, alpha_used double, steps long, pairs long, distinct long, s double")
    return edges.repartition(len(settings), "setting").groupBy("setting").applyInArrow(finish, "setting string, " + INDEX)


def build_index(points: DataFrame, method: str, params: G.Params = G.Params(), router: Router | None = None, metric: str = "l2", rho: float = 0.0) -> DataFrame:
    """Index rows of one method. A local graph of one shard has the exact K-NN graph, whatever the number of points."""
    if router is None and method in G.LOCAL:
        return build_swept(points, {method: (method, params)}, metric).drop("setting")
    return build_indexes(points, {method: (method, params)}, router, metric, rho).drop("setting")


def edges_of(index: DataFrame, level: int = 0, repairs: bool = True) -> DataFrame:
    """(shard, src, dst, dist, rank) of an index's layer; without ``repairs`` only selected edges, which come first in each row."""
    if not repairs:
        index = index.withColumns({c: F.slice(c, 1, F.size(c) - F.col("n_repair")) for c in ("nbrs", "dists")})
    pairs = index.where(F.col("level") == level).select("shard", "src", F.posexplode(F.arrays_zip("nbrs", F.coalesce("dists", F.transform("nbrs", lambda _: F.lit(None).cast("double"))).alias("dists"))).alias("at", "e"))
    return pairs.select("shard", "src", F.col("e.nbrs").alias("dst"), F.col("e.dists").alias("dist"), (F.col("at") + 1).cast("int").alias("rank"))


def measured_edges(points: DataFrame, index: DataFrame, metric: str = "l2") -> DataFrame:
    """(setting, src, dst, dist, degree, true) of index rows: each edge with its stored distance and with that of the points themselves.

    All vectors are broadcast, so none is joined to an edge.
    """
    spark = points.sparkSession
    ship_package(spark)
    space = Metric(metric)
    ids, _, x = vectors_in_order(points, space)
    shared = spark.sparkContext.broadcast((ids, x))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x = shared.value
        for batch in batches:
            # Edges of a few rows at a time: each has two vectors in memory.
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                size = np.diff(part.column(2).offsets.to_numpy()).astype(np.int32)
                row, dst = np.repeat(np.arange(len(size)), size), part.column(2).flatten()
                src = part.column(1).take(pa.array(row))
                true = space.rows(x[np.searchsorted(ids, src.to_numpy())], x[np.searchsorted(ids, dst.to_numpy())])
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(row)), src, dst, part.column(3).flatten(), pa.array(size[row]), pa.array(true)], ["setting", "src", "dst", "dist", "degree", "true"])

    return index.select("setting", "src", "nbrs", "dists").mapInArrow(run, "setting string, src long, dst long, dist double, degree int, true double")


# -- K-NN graph by refinement --------------------------------------------------

def nn_descent(points: DataFrame, k: int, rho: float = 1.0, delta: float = 0.001, rounds: int = 10, metric: str = "l2", seed: int = 5) -> DataFrame:
    """(src, dst, dist, rank): approximate K-NN graph over all points, without shards.

    Each round lets the neighbours of a pivot, forward and reverse, meet. A
    pivot takes at most rho * K new and old neighbours of either direction,
    chosen by hash, so hubs stay bounded by the method's own sampling. Rounds are
    written to the shared folder and stop when few entries change.
    """
    spark = points.sparkSession
    ship_package(spark)
    space = Metric(metric)
    base = stage(points.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("e")), "nnd-points")
    n = base.count()
    if n < 2:
        return spark.createDataFrame([], EDGES)
    take = max(1, int(rho * k))
    tasks = max(2, spark.sparkContext.defaultParallelism)

    def measured(pairs: DataFrame) -> DataFrame:
        """(src, dst, dist) with distances of pairs (src, dst)."""
        both = pairs.join(base.select(F.col("id").alias("src"), F.col("e").alias("se")), "src").join(base.select(F.col("id").alias("dst"), F.col("e").alias("de")), "dst")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    d = space.rows(space.prepare(to_matrix(batch.column(2))), space.prepare(to_matrix(batch.column(3))))
                    yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(d)], ["src", "dst", "dist"])

        return both.select("src", "dst", "se", "de").mapInArrow(run, "src long, dst long, dist double")

    # Start: neighbours in hashed orders. Each order is a chain of points, cut into runs.
    starts = None
    for t in range(3):
        run_of = F.pmod(F.xxhash64("id", F.lit(seed + t)), F.lit(max(1, n // (k + 1))))
        group = base.select("id", run_of.alias("run"))
        pairs = group.alias("a").join(group.alias("b"), "run").where("a.id <> b.id").select(F.col("a.id").alias("src"), F.col("b.id").alias("dst"))
        starts = pairs if starts is None else starts.union(pairs)
    best = W.partitionBy("src").orderBy("dist", "dst")
    trim = lambda df: df.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    graph = stage(trim(measured(starts.distinct())).withColumn("is_new", F.lit(True)), "nnd-graph")
    for r in range(rounds):
        draw = W.partitionBy("pivot", "is_new", "side").orderBy(F.xxhash64("pivot", "other", F.lit(seed + r)), "other")
        forward = graph.select(F.col("src").alias("pivot"), F.col("dst").alias("other"), "is_new", F.lit(0).alias("side"))
        reverse = graph.select(F.col("dst").alias("pivot"), F.col("src").alias("other"), "is_new", F.lit(1).alias("side"))
        lists = forward.union(reverse).withColumn("at", F.row_number().over(draw)).where(F.col("at") <= take)
        pivots = lists.groupBy("pivot").agg(F.collect_set(F.when(F.col("is_new"), F.col("other"))).alias("new"), F.collect_set(F.when(~F.col("is_new"), F.col("other"))).alias("old"))
        meet = pivots.select(F.explode("new").alias("src"), F.array_union("new", "old").alias("all")).select("src", F.explode("all").alias("dst")).where("src <> dst")
        meet = meet.union(meet.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct().join(graph.select("src", "dst"), ["src", "dst"], "left_anti")
        merged = graph.select("src", "dst", "dist", F.lit(False).alias("is_new")).unionByName(measured(meet).withColumn("is_new", F.lit(True)))
        graph = stage(trim(merged), "nnd-graph")
        if graph.where("is_new").count() <= delta * n * k:
            break
    return graph.select("src", "dst", "dist", "rank")


# -- adjacency updates as joins -------------------------------------------------

def backward_candidates(edges: DataFrame) -> DataFrame:
    """Forward and reversed edges together, each (src, dst) once: the candidates of the lazy phase."""
    both = edges.select("src", "dst", "dist").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist"))
    return both.groupBy("src", "dst").agg(F.min("dist").alias("dist"))


def overflow(candidates: DataFrame, m: int) -> DataFrame:
    """(src, n): vertices with more candidates than the cap, which are pruned once."""
    return candidates.groupBy("src").agg(F.count("*").alias("n")).where(F.col("n") > m)


def cap_nearest(edges: DataFrame, m: int) -> DataFrame:
    """The conventional cut to the m nearest, which loses long edges."""
    by = W.partitionBy("src").orderBy("dist", "dst")
    return edges.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= m).select("src", "dst", "dist", "rank")


def reachable(edges: DataFrame, entry: int, rounds: int = 1000) -> DataFrame:
    """(id, hops) of the vertices a walk from ``entry`` reaches: a frontier join each round."""
    spark = edges.sparkSession
    links = stage(edges.select("src", "dst"), "bfs-edges")
    seen = stage(spark.createDataFrame([(entry, 0)], "id long, hops int"), "bfs-seen")
    for hop in range(1, rounds + 1):
        frontier = seen.where(F.col("hops") == hop - 1).select(F.col("id").alias("src"))
        new = links.join(frontier, "src", "left_semi").select(F.col("dst").alias("id")).distinct().join(seen, "id", "left_anti").withColumn("hops", F.lit(hop))
        new = stage(new, "bfs-new")
        if not new.take(1):
            return seen
        seen = stage(seen.unionByName(new), "bfs-seen")
    raise RuntimeError("the walk is deeper than the round limit")


def exact_entry(points: DataFrame) -> int:
    """The point nearest to the coordinate-wise mean."""
    x = points.select("vec_id", F.posexplode("embedding").alias("i", "v"))
    centre = [r.m for r in x.groupBy("i").agg(F.avg("v").alias("m")).orderBy("i").collect()]  # one number for each dimension
    diff = F.zip_with("embedding", F.array(*map(F.lit, centre)), lambda a, b: (a - b) * (a - b))
    return points.agg(F.min_by("vec_id", F.struct(F.aggregate(diff, F.lit(0.0), lambda s, z: s + z), F.col("vec_id")))).first()[0]
