"""Shared working storage: tables that cut lineage and survive the loss of executors.

Everything intermediate goes below the folder that the cluster names in
``spark.checkpoint.dir``; a folder of our own is made only where none is set (local tests).
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark import SparkContext
from pyspark.sql import DataFrame, SparkSession

SHUFFLE_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_own_root: str | None = None
_scopes: list[list[str]] = []
_left: list[str] = []


@atexit.register
def _clean() -> None:
    """Delete what this driver left below the shared root, if its session still lives."""
    sc = SparkContext._active_spark_context
    if sc is None or sc._jsc is None:
        return
    for path in _left:
        target = sc._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(sc._jsc.hadoopConfiguration()).delete(target, True)


def _hadoop_path(spark: SparkSession, path: str):
    """(Hadoop path, its file system)."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target, target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def shared_root(spark: SparkSession) -> str:
    """Folder that the driver and all executors can reach, as a URI with its scheme.

    A folder named without a scheme lies on the cluster's default file system, for Spark's writers and
    for code on executors alike.
    """
    global _own_root
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if not named and current.isDefined():
        named = current.get()
    if not named:
        if _own_root is None:
            _own_root = tempfile.mkdtemp(prefix="spreadlab-")
            atexit.register(shutil.rmtree, _own_root, True)
        spark.sparkContext.setCheckpointDir(_own_root)
        named = spark.sparkContext._jsc.sc().getCheckpointDir().get()
    target, fs = _hadoop_path(spark, named)
    return fs.makeQualified(target).toString().rstrip("/")


def scratch_path(spark: SparkSession, label: str) -> str:
    """A fresh folder name below the shared root."""
    path = f"{shared_root(spark)}/spreadlab-{label}-{uuid.uuid4().hex}"
    _left.append(path)
    for scope in _scopes:
        scope.append(path)
    return path


@contextmanager
def scratch_scope(spark: SparkSession) -> Iterator[list[str]]:
    """Deletes at its end the scratch folders made within, but for those taken off the list that it gives."""
    made: list[str] = []
    _scopes.append(made)
    try:
        yield made
    finally:
        _scopes.remove(made)
        for path in made:
            drop_scratch(spark, path)


def materialize(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as Parquet below the shared root and read it back (columnar, replicated, lineage cut).

    The shuffles that the write made are deleted with its end, since nothing else can read them; otherwise they
    would stay until the driver's next collection of garbage.
    """
    spark = df.sparkSession
    path = scratch_path(spark, label)
    was = spark.conf.get(SHUFFLE_CLEANUP, None)
    spark.conf.set(SHUFFLE_CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        if was is None:
            spark.conf.unset(SHUFFLE_CLEANUP)
        else:
            spark.conf.set(SHUFFLE_CLEANUP, was)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def discard(*frames: DataFrame | None) -> None:
    """Delete the tables of materialized frames that nothing reads any more."""
    for df in frames:
        if df is not None and (path := getattr(df, "_scratch", None)):
            drop_scratch(df.sparkSession, path)


def drop_scratch(spark: SparkSession, path: str) -> None:
    """Delete a scratch folder through Spark's file system layer."""
    target, fs = _hadoop_path(spark, path)
    fs.delete(target, True)
    if path in _left:
        _left.remove(path)


def ship_package(spark: SparkSession) -> None:
    """Send this package to the Python workers once a session, so they import it wherever they run."""
    sc = spark.sparkContext
    if getattr(sc, "_spreadlab_sent", False):
        return
    home = Path(__file__).resolve().parent
    folder = Path(tempfile.mkdtemp(prefix="spreadlab-zip-"))
    atexit.register(shutil.rmtree, folder, True)
    archive = folder / "spreadlab_package.zip"
    with zipfile.ZipFile(archive, "w", zipfile.ZIP_DEFLATED) as out:
        for file in sorted(home.rglob("*.py")):
            out.write(file, str(file.relative_to(home.parent)))
    sc.addPyFile(str(archive))
    sc._spreadlab_sent = True

