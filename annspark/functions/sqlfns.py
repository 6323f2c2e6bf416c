"""Functions for SQL: distances, vector helpers, a top-k merge, and table functions over an index."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.functions.beam import beam_search
from annspark.functions.graphs import search_layered
from annspark.functions.metric import Metric
from annspark.operators.exact import to_matrix
from annspark.operators.search import _graph_of
from annspark.plans.session import ship_package

#: Vertices an index may have to be broadcast whole to table functions.
TABLE_LIMIT = 200_000


def distance(name: str):
    """An Arrow function of two vector columns; rows with a null or of unequal length give null."""
    space = Metric(name)

    @F.arrow_udf("double")
    def run(a: pa.Array, b: pa.Array) -> pa.Array:
        out: list[float | None] = []
        for x, y in zip(a.to_pylist(), b.to_pylist()):
            if x is None or y is None or len(x) != len(y) or None in x or None in y:
                out.append(None)
            else:
                p = space.prepare(np.array([x, y], float))
                out.append(float(space.rows(p[:1], p[1])[0]))
        return pa.array(out, pa.float64())

    return run


@F.arrow_udf("array<double>")
def unit_norm(a: pa.Array) -> pa.Array:
    out = []
    for x in a.to_pylist():
        norm = None if x is None or None in x else float(np.linalg.norm(x))
        out.append([v / norm for v in x] if norm else None)
    return pa.array(out, pa.list_(pa.float64()))


@F.pandas_udf("array<long>")
def topk_merge(dist: pd.Series, ids: pd.Series, k: pd.Series) -> list:
    """Grouped: the ids of the k smallest (dist, id); k is the same on all rows of a group."""
    order = np.lexsort((ids.to_numpy(), dist.to_numpy()))[: int(k.iloc[0])]
    return ids.to_numpy()[order].tolist()


def register(spark: SparkSession) -> None:
    """Make the scalar and grouped functions known to SQL."""
    ship_package(spark)
    for name in ("l2", "l1", "chord", "angular"):
        spark.udf.register(f"{name}_distance", distance(name))
    spark.udf.register("unit_norm", unit_norm)
    spark.udf.register("topk_merge", topk_merge)


def register_index(spark: SparkSession, index: DataFrame, prefix: str = "ann", metric: str = "l2", limit: int = TABLE_LIMIT) -> None:
    """``<prefix>_topk(qvec, k, width)`` and ``<prefix>_trace(qvec)`` over a one-shard index small enough to broadcast."""
    ship_package(spark)
    rows = index.toArrow() if index.where("level = 0").count() <= limit else None
    if rows is None:
        raise ValueError(f"table functions take indexes of at most {limit} vertices; use search_index")
    if len(set(rows.column("shard").to_pylist())) > 1:
        raise ValueError("table functions take one shard")
    space = Metric(metric)
    shared = spark.sparkContext.broadcast(rows)
    held: dict = {}

    def graph():
        if "g" not in held:
            held["g"] = _graph_of(shared.value, space)
        return held["g"]

    class TopK:
        def eval(self, qvec: list, k: int, width: int) -> Iterator[tuple]:
            g, ids, x = graph()
            got = search_layered(g, x, space.prepare(np.array([qvec], float)), max(k, width), k, space)
            for rank, (i, d) in enumerate(zip(got.ids[0], got.dist[0]), 1):
                if i >= 0:
                    yield rank, int(ids[i]), float(d)

    class Trace:
        def eval(self, qvec: list) -> Iterator[tuple]:
            g, ids, x = graph()
            got = beam_search(g.adjacencies[0], x, space.prepare(np.array([qvec], float)), g.entry, 1, 1, space, traces=True)
            for hop, (i, d) in enumerate(got.traces[0]):
                yield hop, int(ids[i]), float(d)

    spark.udtf.register(f"{prefix}_topk", F.udtf(TopK, returnType="rank int, vec_id long, dist double"))
    spark.udtf.register(f"{prefix}_trace", F.udtf(Trace, returnType="hop int, vec_id long, dist double"))
