"""Batches of changes: consecutive slices of temporal edges, and random ones."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

PRELOAD = 0.9


def temporal_slices(temporal: DataFrame, fraction: float, batches: int) -> tuple[DataFrame, DataFrame]:
    """(preloaded edges, (batch, op, src, dst) rows): the first nine tenths by time, then equal slices.

    Numbering rows by time needs a global order; feeds that arrive in order do not need this fixture.
    """
    numbered = temporal.withColumn("k", F.row_number().over(Window.orderBy("ts", "src", "dst")) - 1)
    total = temporal.count()
    head, size = int(PRELOAD * total), max(1, round(fraction * total))
    pre = numbered.where(F.col("k") < head).select("src", "dst")
    tail = numbered.where((F.col("k") >= head) & (F.col("k") < head + size * batches))
    return pre, tail.select(F.floor((F.col("k") - head) / size).cast("long").alias("batch"), F.lit("ins").alias("op"), "src", "dst")


def random_batch(edges: DataFrame, fraction: float, seed: int = 42) -> DataFrame:
    """(op, src, dst): four fifths insertions, one fifth deletions, no loop deleted and no vertex gained or lost.

    Picks follow md5 digests, so any SQL engine gives the same batch.
    """
    spark = edges.sparkSession
    v = edges.select(F.col("src").alias("v")).union(edges.select("dst")).distinct()
    numbered = v.withColumn("k", F.row_number().over(Window.orderBy("v")) - 1)
    total, n = edges.count(), v.count()
    size = max(1, round(fraction * total))
    n_del = round(0.2 * size)
    n_ins = size - n_del
    gone = edges.where("src <> dst").withColumn("h", F.md5(F.concat_ws("|", F.lit(str(seed)), "src", "dst"))).orderBy("h", "src", "dst").limit(n_del)
    spot = lambda tag: F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|{tag}|"), F.col("id").cast("string"))), 1, 8), 16, 10).cast("long") % n
    drawn = spark.range(4 * n_ins + 16).select("id", spot("s").alias("a"), spot("t").alias("b"))
    named = drawn.join(numbered.select(F.col("k").alias("a"), F.col("v").alias("src")), "a").join(numbered.select(F.col("k").alias("b"), F.col("v").alias("dst")), "b")
    fresh = named.where("src <> dst").groupBy("src", "dst").agg(F.min("id").alias("id")).join(edges, ["src", "dst"], "left_anti").orderBy("id").limit(n_ins)
    return fresh.select(F.lit("ins").alias("op"), "src", "dst").unionByName(gone.select(F.lit("del").alias("op"), "src", "dst"))
