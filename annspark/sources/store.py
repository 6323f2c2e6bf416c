"""An index store on the shared file system: versions, tombstones and a delta buffer.

Each version is a folder with index rows, the router and a manifest. The
manifest is written last and names the version, so readers see a whole version
or none. Deletions are ids in a tombstone table; new vectors wait in a delta
table, are searched by scan, and are folded in by a rebuild.
"""

from __future__ import annotations

import json
import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.functions.graphs import Params
from annspark.operators import exact
from annspark.operators.build import INDEX, Router, build_index, train_router
from annspark.operators.search import search_index
from annspark.plans.session import stage

POINTS = "vec_id long, embedding array<double>"


class IndexStore:
    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def _fs(self):
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path
        return path(self.path).getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), path

    def versions(self) -> list[int]:
        """Versions whose manifest is complete."""
        fs, path = self._fs()
        if not fs.exists(path(self.path)):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(path(self.path))]
        return sorted(int(n[1:]) for n in names if n.startswith("v") and n[1:].isdigit() and fs.exists(path(f"{self.path}/{n}/manifest/_SUCCESS")))

    def manifest(self, version: int | None = None) -> dict:
        version = self.versions()[-1] if version is None else version
        return json.loads(self.spark.read.text(f"{self.path}/v{version}/manifest").first()[0])

    def write(self, points: DataFrame, method: str, params: Params, shards: int = 1, metric: str = "l2", rho: float = 0.0) -> int:
        """Build and commit the next version; returns its number."""
        version = (self.versions() or [0])[-1] + 1
        root = f"{self.path}/v{version}"
        router = train_router(points, shards, metric) if shards > 1 else None
        index = build_index(points, method, params, router, metric, rho)
        index.repartition("shard").sortWithinPartitions("src").write.mode("overwrite").partitionBy("shard").parquet(f"{root}/index")
        about = {"version": version, "method": method, "metric": metric, "shards": shards, "rho": rho, "params": params.__dict__, "written": time.time()}
        about["centroids"] = router.centroids.tolist() if router else None
        self.spark.createDataFrame([(json.dumps(about),)], "value string").coalesce(1).write.mode("overwrite").text(f"{root}/manifest")
        return version

    def index(self, version: int | None = None) -> tuple[DataFrame, Router | None, dict]:
        about = self.manifest(version)
        rows = self.spark.read.schema(INDEX).parquet(f"{self.path}/v{about['version']}/index")
        router = Router(np.array(about["centroids"]), about["metric"]) if about["centroids"] else None
        return rows, router, about

    def _table(self, name: str, schema: str) -> DataFrame:
        fs, path = self._fs()
        where = f"{self.path}/{name}"
        return self.spark.read.schema(schema).parquet(where) if fs.exists(path(where)) else self.spark.createDataFrame([], schema)

    def _files(self, name: str) -> list[str]:
        """The committed files of a table, as they are now."""
        fs, path = self._fs()
        where = path(f"{self.path}/{name}")
        return [s.getPath().toString() for s in fs.listStatus(where) if s.getPath().getName().endswith(".parquet")] if fs.exists(where) else []

    def _read(self, files: list[str], schema: str) -> DataFrame:
        return self.spark.read.schema(schema).parquet(*files) if files else self.spark.createDataFrame([], schema)

    def insert(self, points: DataFrame) -> None:
        points.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>")).write.mode("append").parquet(f"{self.path}/delta")

    def delete(self, ids: DataFrame) -> None:
        ids.select(F.col("vec_id").cast("long")).write.mode("append").parquet(f"{self.path}/tombstones")

    def live_delta(self) -> DataFrame:
        return self._table("delta", POINTS).join(self._table("tombstones", "vec_id long"), "vec_id", "left_anti")

    def search(self, queries: DataFrame, k: int, width: int, probes: int = 1) -> DataFrame:
        """(q_id, rank, vec_id, dist): the index without tombstones, merged with a scan of the delta.

        It is asked for more than k, and queries that deletions leave with fewer are asked again with twice as many, up to the index's size.
        """
        rows, router, about = self.index()
        dead = self._table("tombstones", "vec_id long").distinct()
        fetch = k + min(dead.count(), width)
        fresh = exact.exact_knn(self.live_delta(), queries, k, about["metric"]).select("q_id", "vec_id", "dist")
        held = rows.where("level = 0").select(F.col("src").alias("vec_id")).distinct()
        n, need = held.count(), min(k, held.join(dead, "vec_id", "left_anti").count())
        answers, left = fresh, stage(queries, "store-queries")
        while need:
            found = search_index(rows, left, fetch, [max(width, fetch)], router, probes, about["metric"]).select("q_id", "vec_id", "dist")
            live = stage(exact.top_k(found.join(dead, "vec_id", "left_anti").distinct(), k), "store-found")
            full = live.groupBy("q_id").agg(F.count("*").alias("c")).where(F.col("c") >= need).select("q_id")
            done = live if fetch >= n else live.join(full, "q_id", "left_semi")
            answers = answers.unionByName(done.select("q_id", "vec_id", "dist"))
            if fetch >= n:
                break
            left = stage(left.join(full, "q_id", "left_anti"), "store-left")
            if not left.take(1):
                break
            fetch = min(n, 2 * fetch)
        return exact.top_k(answers.distinct(), k)

    def rebuild(self) -> int:
        """Fold the delta in and the tombstones out, as a new version; then remove what was folded.

        Inserts and deletions that come while it runs stay for the next rebuild.
        """
        rows, _, about = self.index()
        delta_files, dead_files = self._files("delta"), self._files("tombstones")
        dead, delta = self._read(dead_files, "vec_id long").distinct(), self._read(delta_files, POINTS)
        old = rows.where("level = 0").select(F.col("src").alias("vec_id"), F.col("vec").alias("embedding")).dropDuplicates(["vec_id"])
        kept = old.join(dead, "vec_id", "left_anti").join(delta.select("vec_id"), "vec_id", "left_anti")
        points = kept.unionByName(delta.join(dead, "vec_id", "left_anti").dropDuplicates(["vec_id"]))
        version = self.write(points, about["method"], Params(**about["params"]), about["shards"], about["metric"], about["rho"])
        fs, path = self._fs()
        # The delta goes first: a tombstone that outlives its rows harms nothing, rows that outlive it would come back.
        for name in delta_files + dead_files:
            fs.delete(path(name), False)
        return version
