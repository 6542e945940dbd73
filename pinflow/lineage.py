"""Lineage cuts: intermediate tables in the folder that the cluster shares."""

from __future__ import annotations

import atexit
import gc
import re
import tempfile
import threading
import time
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession, functions as F

_made: list[tuple[SparkSession, str]] = []
BROADCAST = 1 << 18  # bytes of a written or shuffled table; in memory it may be a hundred times as large
_lock, _lowered = threading.Lock(), {}  # by session: how many threads are inside small_broadcasts, and its settings before


def scratch_path(spark: SparkSession, label: str, kept: bool = False) -> str:
    """A fresh path below spark.checkpoint.dir; below a temporary folder only where that is unset and all runs on one machine."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        master = spark.conf.get("spark.master", "local")
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = getattr(spark, "_pinflow_scratch", None)
        if base is None:
            base = spark._pinflow_scratch = tempfile.mkdtemp(prefix="pinflow-")
    path = f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"
    if kept:  # until the session ends
        _made.append((spark, path))
    return path


def _bytes(size: str) -> int:
    """A Spark setting of bytes as a number: plain, or with a unit."""
    found = re.fullmatch(r"\s*(-?\d+)\s*([kmgtp]?)b?\s*", size.lower())
    return int(found[1]) << 10 * " kmgtp".index(found[2] or " ")


@contextmanager
def small_broadcasts(spark: SparkSession):
    """Plans that run inside broadcast no table above ``BROADCAST`` bytes, unless a hint asks for it.

    The planner goes by compressed bytes, and the driver builds what is broadcast in its own memory: a join's smaller side
    that stays below the session's threshold on disk fills a small driver in rows. Of several threads the last one out
    puts the session's settings back."""
    name, adaptive = "spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold"
    with _lock:
        inside, before = _lowered.get(id(spark), (0, None))
        if not inside:
            before = {name: spark.conf.get(name), adaptive: spark.conf.get(adaptive, None)}
            for n, size in before.items():
                if size is not None and _bytes(size) > BROADCAST:
                    spark.conf.set(n, str(BROADCAST))
        _lowered[id(spark)] = inside + 1, before
    try:
        yield
    finally:
        with _lock:
            inside = _lowered[id(spark)][0] - 1
            _lowered[id(spark)] = inside, before
            if not inside:
                del _lowered[id(spark)]
                for n, size in before.items():
                    if size is not None:
                        spark.conf.set(n, size)


def cut(df: DataFrame, label: str, by: str | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends here, and lost executors lose nothing.

    by: a column of few values; rows lie in a folder per value, and filters on it read only theirs."""
    spark = df.sparkSession
    path = scratch_path(spark, label, kept=True)
    with small_broadcasts(spark):
        (df.repartition(by, F.floor(F.rand(7) * 32)) if by else df).write.parquet(path, partitionBy=by)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Delete what ``cut`` wrote for ``df``, once no later plan reads it."""
    files = df.inputFiles()[:1]
    for spark, path in list(_made):
        if files and f"/{path.rsplit('/', 1)[-1]}/" in files[0]:
            remove(spark, path)
            _made.remove((spark, path))


def write_in_turn(rows: DataFrame, path: str, order: str, size: int) -> None:
    """Files of ``size`` rows in order, whose times tell a file stream that order: one job, by one task."""
    spark = rows.sparkSession
    rows.repartition(1).sortWithinPartitions(order).write.option("maxRecordsPerFile", size).parquet(path)
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = folder.getFileSystem(spark._jsc.hadoopConfiguration())
    files = sorted((f.getPath() for f in fs.listStatus(folder) if f.getPath().getName().startswith("part-")), key=lambda f: f.getName().split("-c")[-1].split(".")[0].zfill(12))
    last = int(time.time()) * 1000
    for i, f in enumerate(files):
        fs.setTimes(f, last - 10 * (len(files) - i), -1)


def release(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of plans that nothing refers to any more, now and not at some later collection."""
    for _ in range(2):  # the first round may meet plans that Spark's listeners still hold
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.5)


def remove(spark: SparkSession, path: str) -> None:
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _sweep() -> None:
    for spark, path in _made:
        try:
            remove(spark, path)
        except Exception:  # the JVM is gone already: the shared folder is the cluster's to clean
            return
