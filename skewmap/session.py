"""Session helpers: shipping the package to Python workers, and tables in the folder that a cluster shares."""

from __future__ import annotations

import contextlib
import functools
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator
from pathlib import Path

from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Give this package to the session's Python workers through Spark's own file service, once per application."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return spark
    root = Path(__file__).resolve().parent
    handle, name = tempfile.mkstemp(prefix="skewmap-", suffix=".zip")
    os.close(handle)
    with zipfile.ZipFile(name, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent).as_posix())
    spark.sparkContext.addPyFile(name)
    _shipped.add(app)
    return spark


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share: ``spark.checkpoint.dir``; a temporary one only if it is unset and Spark is one process."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="skewmap-shared-")
        spark.sparkContext.setCheckpointDir(found)
    return found


#: What ``cleaned`` functions that are running have made so far: stored tables and broadcasts.
_scopes: list[list[DataFrame | Broadcast]] = []
#: Broadcasts that lazy results made outside of such functions still read.
_loose: list[Broadcast] = []


def shared(spark: SparkSession, value) -> Broadcast:
    """Broadcast of a value of bounded size. It is destroyed with the function that made it if that is ``cleaned``."""
    handle = spark.sparkContext.broadcast(value)
    (_scopes[-1] if _scopes else _loose).append(handle)
    return handle


def release() -> None:
    """Take the broadcasts of earlier lazy results off the executors; a result that is read again fetches its own anew."""
    while _loose:
        _loose.pop().unpersist()


def _path(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def stored(df: DataFrame, name: str = "step", **options: str) -> DataFrame:
    """``df`` as Parquet in the shared folder, read again: its lineage is cut, and lost executors cost nothing.

    The files go when the application ends, or with the function that made them if it is ``cleaned``.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/skewmap-{name}-{uuid.uuid4().hex}"
    df.write.options(**options).parquet(path)
    fs, where = _path(spark, path)
    fs.deleteOnExit(where)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_at = path
    if _scopes:
        _scopes[-1].append(out)
    return out


def discard(made: DataFrame | Broadcast) -> None:
    """Delete the files of a stored table, or a broadcast, that nothing reads any more."""
    if isinstance(made, Broadcast):
        made.destroy()
    else:
        fs, where = _path(made.sparkSession, made._stored_at)
        fs.delete(where, True)


def cleaned(make: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
    """The function's result is stored, and every table and broadcast that it made on the way is deleted."""

    @functools.wraps(make)
    def run(*args, **kwargs) -> DataFrame:
        inner: list[DataFrame | Broadcast] = []
        _scopes.append(inner)
        try:
            result = make(*args, **kwargs)
            _scopes[-1] = []
            out = stored(result, make.__name__)
        finally:
            _scopes.pop()
            for made in inner:
                discard(made)
        if _scopes:
            _scopes[-1].append(out)
        return out

    return run


@contextlib.contextmanager
def scratch() -> Iterator[None]:
    """Every table and broadcast that is made inside is deleted at the end."""
    inner: list[DataFrame | Broadcast] = []
    _scopes.append(inner)
    try:
        yield
    finally:
        _scopes.pop()
        for made in inner:
            discard(made)


def partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
