"""Where intermediate tables go: the folder that every executor shares."""

from __future__ import annotations

import atexit
import gc
import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Paths of this application's scratch tables; they go when it ends.
_SCRATCH: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder of the session. Only a session in one process (a test) may do without one and gets a local folder."""
    context = spark.sparkContext
    where = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not where:
        if not re.match(r"local(\[|$)", context.master or ""):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        where = tempfile.mkdtemp(prefix="graphwatch-")
    if not context.getCheckpointDir():
        context.setCheckpointDir(where)
    return where


def _remove_scratch() -> None:
    for spark, path in _SCRATCH:
        try:
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
        except Exception:  # noqa: BLE001  the session has ended before; what is left is scratch
            return


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path below the shared folder, which goes when the application ends."""
    if not _SCRATCH:
        atexit.register(_remove_scratch)
    path = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    _SCRATCH.append((spark, path))
    return path


@contextmanager
def passing_shuffles(spark: SparkSession) -> Iterator[None]:
    """What runs to its end in here leaves no shuffles behind; else they stay until the driver happens to collect its garbage."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(name)
        else:
            spark.conf.set(name, before)


#: Tables of one query: session, weak reference to what every plan on the table holds, path.
_PASSING: list[tuple] = []


def _remove_unreached(spark: SparkSession) -> None:
    """Remove the passing tables that no DataFrame reaches any more."""
    if not _PASSING:
        return
    gc.collect()
    spark._jvm.System.gc()
    for entry in list(_PASSING):
        owner, held, path = entry
        if owner is spark and held.get() is None:
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
            _PASSING.remove(entry)


def passing_table(df: DataFrame, name: str) -> DataFrame:
    """Like table, but its files go when a later such table is made and nothing that was made of this one is held any more."""
    spark = df.sparkSession
    _remove_unreached(spark)
    with passing_shuffles(spark):
        out = table(df, name)
    files = out._jdf.queryExecution().analyzed().relation().location()
    _PASSING.append((spark, spark._jvm.java.lang.ref.WeakReference(files), _SCRATCH[-1][1]))
    return out


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint, which survives the loss of executors."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def table(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet in the shared folder and read it back, without the partitioning it had."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
