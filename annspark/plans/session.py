"""Session helpers: code shipping and the shared staging folder."""

from __future__ import annotations

import io
import os
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_PACKAGE = Path(__file__).resolve().parents[1]
_shipped: set[str] = set()
_own_dirs: dict[str, str] = {}
_staged: dict[str, list[str]] = {}
_releases: dict[str, int] = {}


def ship_package(spark: SparkSession) -> None:
    """Make this package importable in every Python worker, once per application.

    The zip goes through Spark's own file server, so executors need no shared
    folder and no particular PYTHONPATH.
    """
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    buffer = io.BytesIO()
    with zipfile.ZipFile(buffer, "w", zipfile.ZIP_DEFLATED) as z:
        for path in sorted(_PACKAGE.rglob("*.py")):
            z.write(path, path.relative_to(_PACKAGE.parent).as_posix())
    folder = tempfile.mkdtemp(prefix="annspark-code-")
    target = os.path.join(folder, "annspark_code.zip")
    with open(target, "wb") as f:
        f.write(buffer.getvalue())
    sc.addPyFile(target)
    _shipped.add(sc.applicationId)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir.

    Only where the setting is absent and all runs on one machine a folder of
    this application's own is used; a cluster must name one.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _own_dirs:
        _own_dirs[app] = tempfile.mkdtemp(prefix="annspark-shared-")
    return _own_dirs[app]


def staging_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder, remembered for release_staged."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _staged.setdefault(spark.sparkContext.applicationId, []).append(path)
    return path


def releases(spark: SparkSession) -> int:
    """How often this application has released its staged tables: what was staged before is gone."""
    return _releases.get(spark.sparkContext.applicationId, 0)


def release_staged(spark: SparkSession) -> int:
    """Delete what this application has staged so far; call it when no result that reads it is needed any more."""
    app = spark.sparkContext.applicationId
    paths = _staged.pop(app, [])
    _releases[app] = releases(spark) + 1
    _delete(spark, paths)
    return len(paths)


def _delete(spark: SparkSession, paths: list[str]) -> None:
    jvm = spark.sparkContext._jvm
    for path in paths:
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Delete at the end what was staged inside, for work whose results are plain values by then."""
    app = spark.sparkContext.applicationId
    before = set(_staged.get(app, []))
    try:
        yield
    finally:
        own = [path for path in _staged.get(app, []) if path not in before]
        _staged[app] = [path for path in _staged.get(app, []) if path in before]
        _delete(spark, own)


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back.

    This cuts the lineage and survives lost executors; the rows are computed
    once, whatever number of readers follows.
    """
    spark = df.sparkSession
    path = staging_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def path_exists(spark: SparkSession, path: str) -> bool:
    """Ask the path's own file system, so object stores work too."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)
