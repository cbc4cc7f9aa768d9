"""Shared-folder storage: cutting lineage with tables every executor can read.

The cluster names a shared folder in ``spark.checkpoint.dir``.  Intermediate tables go there as
Parquet; a machine-local folder is used only where that setting is absent (tests, ``local[*]``).
"""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_SETTING = "spark.checkpoint.dir"
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_local_default: dict[str, str] = {}


def prepare(spark: SparkSession) -> SparkSession:
    """Make the package importable in Python workers and make sure a checkpoint folder is set."""
    context = spark.sparkContext
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    known = context.environment.get("PYTHONPATH", "")
    if root not in known.split(os.pathsep):
        context.environment["PYTHONPATH"] = os.pathsep.join(x for x in (root, known) if x)
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(shared_dir(spark))
    return spark


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share: the cluster's setting, else one local default per application."""
    named = spark.sparkContext.getConf().get(_SETTING, None) or spark.conf.get(_SETTING, None)
    if named:
        return named.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _local_default:
        _local_default[app] = tempfile.mkdtemp(prefix="edgesplit-")
    return _local_default[app]


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that nothing has used yet."""
    return f"{shared_dir(spark)}/edgesplit/{name}-{uuid.uuid4().hex}"


def _file_system(spark: SparkSession, path: str):
    """The path's own file system, whatever store it is in, and the path there."""
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    return place.getFileSystem(spark._jsc.hadoopConfiguration()), place


def exists(spark: SparkSession, path: str) -> bool:
    store, place = _file_system(spark, path)
    return bool(store.exists(place))


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder that nothing reads any more; a missing one is no error."""
    store, place = _file_system(spark, path)
    store.delete(place, True)


@contextmanager
def session_value(spark: SparkSession, name: str, value: str) -> Iterator[None]:
    """A setting of the session for a while; the session's own choice comes back."""
    try:
        before = spark.conf.get(name)
    except Exception:  # a Spark without this setting goes on without it
        yield
        return
    spark.conf.set(name, value)
    try:
        yield
    finally:
        spark.conf.set(name, before)


#: Paths of the tables made inside each open ``temporary`` block, the innermost last.
_blocks: list[list[tuple[SparkSession, str]]] = []


@contextmanager
def temporary() -> Iterator[None]:
    """Tables materialised inside are removed at the end: nothing lazy that reads them may leave the block."""
    own: list[tuple[SparkSession, str]] = []
    _blocks.append(own)
    try:
        yield
    finally:
        _blocks.remove(own)
        for spark, path in own:
            remove(spark, path)


def materialise(df: DataFrame, name: str, keep: bool = False, options: dict[str, str] | None = None) -> DataFrame:
    """Write a table to the shared folder and read it back.

    Lineage ends there and survives lost executors, and what the table's own shuffles left on the
    executors' disks is freed at once.  ``keep`` takes the table out of the innermost ``temporary`` block;
    ``options`` are the writer's.
    """
    spark = df.sparkSession
    path = fresh_path(spark, name)
    if open_blocks := _blocks[:-1] if keep else _blocks:
        open_blocks[-1].append((spark, path))
    with session_value(spark, _CLEANUP, "true"):
        df.write.options(**(options or {})).parquet(path)
    return spark.read.schema(df.schema).parquet(path)
