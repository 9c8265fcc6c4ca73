"""Tables in the folder that the driver and all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_own_dir: str | None = None
#: Setting of a session (not of its start) that lets an execution remove its shuffle files.
_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_lock = threading.Lock()
_cleaning: dict[str, list] = {}  # by session: writes under way, and what the setting was


@contextmanager
def own_shuffles_go(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of what is executed inside go when it ends: what they held is in a table.

    The session's setting is put back when the last of several concurrent writes has ended.
    """
    session = spark._jsparkSession.sessionUUID()
    with _lock:
        under_way = _cleaning.setdefault(session, [0, None])
        if under_way[0] == 0:
            under_way[1] = spark.conf.get(_CLEAN, None)
            spark.conf.set(_CLEAN, "true")
        under_way[0] += 1
    try:
        yield
    finally:
        with _lock:
            under_way[0] -= 1
            if under_way[0] == 0:
                spark.conf.unset(_CLEAN) if under_way[1] is None else spark.conf.set(_CLEAN, under_way[1])


def shared_dir(spark: SparkSession) -> str:
    """What ``spark.checkpoint.dir`` names.

    Only where that is unset and the master is local (tests, one machine) a temporary folder
    is made, which goes when the process ends; on a cluster it must be set, as executors do
    not see the driver's folders.
    """
    global _own_dir
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local"):
        raise RuntimeError(f"spark.checkpoint.dir must name a folder that all executors of {master} share")
    if _own_dir is None:
        _own_dir = tempfile.mkdtemp(prefix="series_index_")
        atexit.register(shutil.rmtree, _own_dir, ignore_errors=True)
    return _own_dir


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


_scratch = threading.local()


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Tables and indexes that this thread writes inside go at the end: nothing that is read
    later may lead back to them."""
    outer, _scratch.paths = getattr(_scratch, "paths", None), []
    try:
        yield
    finally:
        paths, _scratch.paths = _scratch.paths, outer
        for path in paths:
            remove(spark, path)


def scratched(path: str) -> str:
    """``path``, which goes with the scratch that is open, if one is."""
    if getattr(_scratch, "paths", None) is not None:
        _scratch.paths.append(path)
    return path


def written(df: DataFrame, name: str, group: int = 128 << 20) -> DataFrame:
    """``df`` written once and read back: lineage ends here and no executor holds the only copy.
    group: bytes of a row group; one task reads at least one, however many tasks there are."""
    path = scratched(fresh_path(df.sparkSession, name))
    with own_shuffles_go(df.sparkSession):
        df.write.option("compression", "zstd").option("parquet.block.size", str(group)).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
