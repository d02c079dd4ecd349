"""What every operator needs from the session as given: shared staging and shipped code."""

from __future__ import annotations

import gc
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()
#: Bytes of an Arrow batch: rows of long texts would else be buffered by tens of megabytes for each task.
ARROW_BYTES, _ARROW = "2m", "spark.sql.execution.arrow.maxBytesPerBatch"


def ship(spark: SparkSession) -> None:
    """Ready the session for Python operators: small Arrow batches, and this package importable in the workers.

    The batch size is set only where it still has its default. The package goes out once for each application, as a
    zip through the driver's own file server, unless PYTHONPATH already reaches it.
    """
    if spark.conf.get(_ARROW, None) in ("67108864b", "64m"):
        spark.conf.set(_ARROW, ARROW_BYTES)
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    _shipped.add(sc.applicationId)
    here = os.path.dirname(os.path.abspath(__file__))
    if any(os.path.isdir(os.path.join(p, "corpuskit")) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p):
        return
    path = os.path.join(os.path.realpath(tempfile.mkdtemp()), "corpuskit.zip")
    with zipfile.ZipFile(path, "w") as z:
        for folder, _, names in os.walk(here):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.join("corpuskit", os.path.relpath(full, here)))
    sc.addPyFile(path)


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or one of our own where it is unset and all runs in one process."""
    sc = spark.sparkContext
    if known := sc.getConf().get("spark.checkpoint.dir"):
        return known
    set_by = sc.getCheckpointDir()
    if set_by is None:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="corpuskit-"))
        set_by = sc.getCheckpointDir()
    return set_by


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


#: Folders of staged tables by application, until they are given up.
_staged: dict[str, list[str]] = {}


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write a DataFrame as Parquet in the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    _staged.setdefault(spark.sparkContext.applicationId, []).append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.staged_at = path
    return out


def delete(spark: SparkSession, path: str) -> None:
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def discard(*tables: DataFrame) -> None:
    """Delete the folders of staged tables that nothing will read again."""
    for df in tables:
        delete(df.sparkSession, df.staged_at)
        _staged[df.sparkSession.sparkContext.applicationId].remove(df.staged_at)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Deletes in the end what is staged inside, but the tables that the yielded function is called on."""
    every = _staged.setdefault(spark.sparkContext.applicationId, [])
    before, kept = set(every), set()

    def keep(df: DataFrame) -> DataFrame:
        kept.add(df.staged_at)
        return df

    try:
        yield keep
    finally:
        for path in [p for p in every if p not in before and p not in kept]:
            delete(spark, path)
            every.remove(path)
        settle(spark)


def staged_paths(spark: SparkSession) -> list[str]:
    """Folders staged in this application that are still there."""
    return list(_staged.get(spark.sparkContext.applicationId, []))


def delete_unread(paths: list[str], docs: DataFrame) -> None:
    """Delete those of the staged folders that docs doesn't read."""
    spark = docs.sparkSession
    read = {f.rsplit("/", 2)[-2] for f in docs.inputFiles()}  # every folder has a name of its own
    every = _staged.get(spark.sparkContext.applicationId, [])
    for path in [p for p in paths if p in every and p.rsplit("/", 1)[-1] not in read]:
        delete(spark, path)
        every.remove(path)
    settle(spark)


def settle(spark: SparkSession) -> None:
    """Let the driver notice plans that are done: their shuffle files go only when their objects are collected."""
    gc.collect()
    spark._jvm.System.gc()
