"""Cutting lineage in the folder that all machines share."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the session's spark.checkpoint.dir; set a folder of our own only where there is none."""
    if spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        return
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="evolrank-checkpoint-"))


_WRITTEN: dict[int, tuple[DataFrame, str, str | None]] = {}  # frames of our own files: (frame, folder, table name)


def _own_folder(spark: SparkSession) -> str:
    ensure_checkpoint_dir(spark)
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return f"{root.rstrip('/')}/evolrank-{uuid.uuid4().hex}"


def written(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it back; ``discard`` removes it."""
    path = _own_folder(df.sparkSession)
    df.write.parquet(path)
    made = df.sparkSession.read.schema(df.schema).parquet(path)
    _WRITTEN[id(made)] = (made, path, None)
    atexit.register(_remove, df.sparkSession, path, None)
    return made


def bucketed(df: DataFrame, key: str, buckets: int) -> DataFrame:
    """Write a table dealt out by ``key``: tables with equal bucket counts join on their keys without an exchange."""
    spark, path = df.sparkSession, _own_folder(df.sparkSession)
    name = path.rsplit("/", 1)[1].replace("-", "_")
    df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).option("path", path).saveAsTable(name)
    made = spark.table(name)
    _WRITTEN[id(made)] = (made, path, name)
    atexit.register(_remove, spark, path, name)
    return made


def discard(*frames: DataFrame | None) -> None:
    """Delete the files of frames of ``written`` and ``bucketed`` that nothing reads any more; others are left alone."""
    for df in frames:
        held = _WRITTEN.pop(id(df), None)
        if held:
            _remove(held[0].sparkSession, held[1], held[2])


def _remove(spark: SparkSession, path: str, name: str | None) -> None:
    try:
        if name:
            spark.sql(f"DROP TABLE IF EXISTS {name}")
        target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # at exit the session may be gone already; a left-over folder does no harm
        pass


def settle(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: the plan starts anew and survives lost executors."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


@contextmanager
def fixed_partitioning(spark: SparkSession):
    """Adaptive execution off: checkpoints then remember how they are partitioned.

    Adjacency and ranks that were once dealt out by the same key join without an
    exchange in every iteration; the sum by target is the only shuffle left.
    """
    key = "spark.sql.adaptive.enabled"
    before = spark.conf.get(key, "true")
    spark.conf.set(key, "false")
    try:
        yield
    finally:
        spark.conf.set(key, before)
