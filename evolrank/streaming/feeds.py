"""Edge feeds: files as a stream, duplicates within a watermark, and ranks kept up to date batch by batch."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LATE = "10 minutes"


def event_stream(spark: SparkSession, folder: str, schema, files_per_batch: int = 64) -> DataFrame:
    """Parquet files of ``folder`` as a stream; new files are read as they arrive."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def without_late_duplicates(edges: DataFrame, late: str = LATE) -> DataFrame:
    """Edges (src, dst, ts) once each within the watermark; state older than that is dropped."""
    return edges.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src", "dst"])


def windowed_edges(edges: DataFrame, width: str = "1 day", late: str = LATE) -> DataFrame:
    """(day, n): edges counted by tumbling window, closed once the watermark has passed."""
    return edges.withWatermark("ts", late).groupBy(F.window("ts", width)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("day"), "n")


def version_writer(out: str, change):
    """A function for ``foreachBatch`` that writes ``change(batch)`` as version=<batch id>.

    A version that is complete already is left alone, so a batch that is replayed
    after a failure has its effect once.
    """

    def write(batch: DataFrame, batch_id: int) -> None:
        jvm = batch.sparkSession.sparkContext._jvm
        done = jvm.org.apache.hadoop.fs.Path(f"{out}/version={batch_id}/_SUCCESS")
        if not done.getFileSystem(batch.sparkSession.sparkContext._jsc.hadoopConfiguration()).exists(done):
            change(batch).write.mode("overwrite").parquet(f"{out}/version={batch_id}")

    return write


def maintain(stream: DataFrame, out: str, checkpoint: str, change):
    """Run a feed to its present end; every micro-batch becomes one version under ``out``."""
    query = stream.writeStream.foreachBatch(version_writer(out, change)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return query


def versions(spark: SparkSession, out: str, schema) -> DataFrame:
    """All versions with their number; a filter on ``version`` prunes folders."""
    return spark.read.option("basePath", out).schema(schema.add("version", "long")).parquet(f"{out}/version=*")
