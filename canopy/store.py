"""Lineage cuts that outlive executors.

Every loop and every multi-use intermediate is written as a Parquet table under
the folder named by ``spark.checkpoint.dir`` and read back.  Such a table is
shared by all executors, so a lost executor costs a task retry and never a
replay of the loop.  ``localCheckpoint`` is not used anywhere.
"""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
import warnings
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

#: How far a written table may be compressed, and a size of files that is small at any rate.
PACKED, SMALL = 16, 1 << 19

_OPEN: dict[str, SparkSession] = {}
_FALLBACK: list[str] = []
_SCOPES: list = []


def reachable(spark: SparkSession) -> SparkSession:
    """Let Python workers of this session import the package from where the driver has it.

    Workers take their PYTHONPATH from the context's environment when a function is shipped.  On a cluster whose
    executors don't share that folder, pass the package with ``--py-files`` as usual; this then changes nothing.
    """
    root = str(Path(__file__).resolve().parent.parent)
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root not in paths:
        env["PYTHONPATH"] = os.pathsep.join([root, *paths])
    return spark


def shared_dir(spark: SparkSession) -> str:
    """The shared folder of the session; in local mode a temporary one where none is set."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    master = spark.conf.get("spark.master", "")
    if not master.startswith("local"):
        raise RuntimeError(f"set spark.checkpoint.dir to a folder that all executors of {master} share")
    if not _FALLBACK:
        warnings.warn("spark.checkpoint.dir is not set: tables are cut in a temporary folder of this machine", stacklevel=3)
        _FALLBACK.append(tempfile.mkdtemp(prefix="canopy-"))
    return f"file://{_FALLBACK[0]}"


class Cut:
    """A written table: ``df`` reads it, ``drop()`` deletes it."""

    def __init__(self, spark: SparkSession, path: str, df: DataFrame):
        self.spark, self.path, self.df = spark, path, df

    def drop(self) -> None:
        if _OPEN.pop(self.path, None) is not None:
            _delete(self.spark, self.path)


@contextmanager
def scope() -> Iterator[Callable[[Cut], Cut]]:
    """Drop the tables written inside when the block ends, but for those handed to the yielded function.

    Kept tables belong to the scope around, if there is one.
    """
    made: list[Cut] = []
    kept: list[Cut] = []

    def keep(c: Cut) -> Cut:
        kept.append(c)
        return c

    _SCOPES.append(made)
    try:
        yield keep
    finally:
        _SCOPES.remove(made)
        for c in made:
            if c not in kept:
                c.drop()
        if _SCOPES:
            _SCOPES[-1].extend(kept)


@contextmanager
def swept(spark: SparkSession) -> Iterator[None]:
    """Delete the shuffle files of each execution inside as it ends; else they stay until the driver collects garbage.

    For code whose results are all written: nothing reads the shuffle of an execution that is over.
    """
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def unsent(df: DataFrame) -> DataFrame:
    """``df``, made of Parquet files, kept from being broadcast where only their compression makes it look small.

    Spark takes the size of the files for that of the rows; a table of ids may have a byte a row, and forty or more
    once it is hashed on the driver.  The mark is on this side of a join alone: the other side may be broadcast.
    Filters, projections and aggregates of a marked table keep the mark; unions and semi-joins lose it, though Spark
    sizes them by the files too, so such a side needs one of its own.
    """
    spark = df.sparkSession
    limit = spark._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    if limit <= 0 or size <= max(limit // PACKED, SMALL):
        return df
    jvm = spark._jvm
    plans = jvm.org.apache.spark.sql.catalyst.plans.logical
    mark = plans.HintInfo(jvm.scala.Some(getattr(getattr(plans, "NO_BROADCAST_HASH$"), "MODULE$")))
    plan = plans.ResolvedHint(df._jdf.queryExecution().analyzed(), mark)
    return DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, plan), spark)


def write(df: DataFrame, name: str = "cut") -> Cut:
    """Write ``df`` once and return the handle of the table."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/canopy-{name}-{uuid.uuid4().hex[:12]}"
    df.write.mode("errorifexists").option("compression", "zstd").parquet(path)
    _OPEN[path] = spark
    made = Cut(spark, path, unsent(spark.read.schema(df.schema).parquet(path)))
    if _SCOPES:
        _SCOPES[-1].append(made)
    return made


def folder(spark: SparkSession, name: str) -> Cut:
    """A path under the shared folder for tables that are added one by one; ``drop()`` deletes it with them."""
    path = f"{shared_dir(spark)}/canopy-{name}-{uuid.uuid4().hex[:12]}"
    _OPEN[path] = spark
    made = Cut(spark, path, spark.range(0).toDF("id"))
    if _SCOPES:
        _SCOPES[-1].append(made)
    return made


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """``df`` with its lineage replaced by a scan of a written table."""
    return write(df, name).df


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _sweep() -> None:
    for path, spark in list(_OPEN.items()):
        try:
            if spark._jsc is not None and not spark._jsc.sc().isStopped():
                _delete(spark, path)
        except Exception:  # the session is gone; the folder's owner cleans up
            pass
    if _FALLBACK:
        import shutil

        shutil.rmtree(_FALLBACK[0], ignore_errors=True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
