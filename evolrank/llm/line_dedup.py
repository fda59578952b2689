"""Line deduplication: keep each line only in the first document that holds it.

Line keys are hashed to 128 bits, range-partitioned on (hash, document,
position) and sorted within partitions.  A streaming first-value window walks
each sorted run; because the document belongs to the partitioning key, a line
that fills a third of the corpus is spread over many partitions instead of one.
The few keys that cross a partition edge (at most one per edge) are stitched by
a table of at most two rows per partition, which is therefore safe to broadcast.
The result is a run-length keep bitmap per document, never text.

Defined results for odd input:

* null or empty text is one empty line, which is never dropped;
* rows with a null doc_id neither lose lines nor claim them for others;
* rows that repeat a doc_id count as one document: they keep the same lines;
  each row is returned;
* an empty table gives an empty result; further columns of any name are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import SPACES, ascii_lower, materialise, table, text_of

MIN_KEY_LENGTH = 10


def hashed_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_length: int = MIN_KEY_LENGTH) -> DataFrame:
    """(d, tk, pos, h1, h2) for every line whose key has at least ``min_length`` code points."""
    text = text_of(docs, text_col)
    lines = (
        docs.where(docs[id_col].isNotNull())
        .select(docs[id_col].alias("d"), F.xxhash64(text).alias("tk"), F.split(text, "\n").alias("lines"))
        .select("d", "tk", F.posexplode("lines").alias("pos", "line"))
        .select("d", "tk", "pos", F.btrim(F.col("line"), F.lit(SPACES)).alias("line"))
        .where(F.length("line") >= min_length)
        .select("d", "tk", "pos", ascii_lower(F.col("line")).alias("k"))
    )
    return lines.select("d", "tk", "pos", F.xxhash64("k").alias("h1"), F.xxhash64(F.lit(1), "k").alias("h2"))


def repeated_line_positions(lines: DataFrame) -> DataFrame:
    """(d, tk, pos) of the lines that an earlier document holds too."""
    order = ["h1", "h2", "d", "pos"]
    ranged = materialise(
        materialise(lines).repartitionByRange(*order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id())
    )
    # First and last key of each range with the first document of each: two rows a partition.
    ends = ranged.groupBy("part").agg(F.min(F.struct("h1", "h2", "d")).alias("lo"), F.max(F.struct("h1", "h2", F.bitwise_not("d").alias("nd"))).alias("hi"))
    edges = (
        ends.select(F.explode(F.array(
            F.struct(F.col("lo.h1").alias("h1"), F.col("lo.h2").alias("h2"), F.col("lo.d").alias("d")),
            F.struct(F.col("hi.h1").alias("h1"), F.col("hi.h2").alias("h2"), F.bitwise_not("hi.nd").alias("d")),
        )).alias("e"))
        .groupBy(F.col("e.h1").alias("h1"), F.col("e.h2").alias("h2"))
        .agg(F.min("e.d").alias("edge_first"))
    )
    run = Window.partitionBy("h1", "h2", "part").orderBy("d", "pos")
    return (
        ranged.withColumn("first_d", F.first("d").over(run))
        .join(F.broadcast(edges), ["h1", "h2"], "left")
        .where(F.col("d") > F.least("first_d", "edge_first"))
        .select("d", "tk", "pos")
    )


def drop_runs(positions: DataFrame) -> DataFrame:
    """Run-length bitmap per document: (d, tk, runs array<struct<start,gap,len>>, n_dropped)."""
    by_doc = Window.partitionBy("d", "tk")
    runs = (
        positions.withColumn("island", F.col("pos") - F.dense_rank().over(by_doc.orderBy("pos")))
        .groupBy("d", "tk", "island")
        .agg(F.min("pos").alias("start"), (F.max("pos") - F.min("pos") + 1).alias("len"))
        .withColumn("gap", F.col("start") - F.coalesce(F.lag(F.col("start") + F.col("len")).over(by_doc.orderBy("start")), F.lit(0)))
    )
    return runs.groupBy("d", "tk").agg(
        F.sort_array(F.collect_list(F.struct("start", "gap", "len"))).alias("runs"), F.sum("len").cast("long").alias("n_dropped")
    )


def line_keep_bitmaps(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_length: int = MIN_KEY_LENGTH) -> DataFrame:
    """Compressed keep bitmaps of the documents that lose lines; all others keep everything."""
    return drop_runs(repeated_line_positions(hashed_lines(docs, id_col, text_col, min_length)))


def _kept_text(text: Column) -> Column:
    lines = F.split(text, "\n")
    last = F.element_at("runs", -1)
    flags = F.concat(
        F.flatten(F.transform("runs", lambda r: F.concat(F.array_repeat(F.lit(True), r["gap"]), F.array_repeat(F.lit(False), r["len"])))),
        F.array_repeat(F.lit(True), F.size(lines) - (last["start"] + last["len"])),
    )
    pairs = F.arrays_zip(lines.alias("line"), flags.alias("keep"))
    kept = F.transform(F.filter(pairs, lambda p: p["keep"]), lambda p: p["line"])
    return F.when(F.col("runs").isNull(), text).otherwise(F.array_join(kept, "\n"))


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All columns of ``docs`` in a struct ``row``, with n_lines, n_dropped and kept_text."""
    text = text_of(docs, text_col)
    keyed = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), docs[id_col].alias("d"), F.xxhash64(text).alias("tk"), text.alias("body"))
    joined = keyed.join(bitmaps.hint("shuffle_hash"), ["d", "tk"], "left")
    body = F.col("body")
    return joined.select(
        "row",
        (F.length(body) - F.length(F.replace(body, F.lit("\n"), F.lit(""))) + 1).cast("long").alias("n_lines"),
        F.coalesce("n_dropped", F.lit(0)).cast("long").alias("n_dropped"),
        _kept_text(body).alias("kept_text"),
    )


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_length: int = MIN_KEY_LENGTH) -> DataFrame:
    return apply_bitmaps(docs, line_keep_bitmaps(docs, id_col, text_col, min_length), id_col, text_col)


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return done.select(F.col("row.doc_id").alias("doc_id"), "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


OP1_SQL = r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents),
keyed AS (
  SELECT doc_id, pos, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
  FROM lines),
firsts AS (SELECT k, min(doc_id) AS first_id FROM keyed WHERE length(k) >= 10 GROUP BY k),
judged AS (
  SELECT keyed.doc_id, pos, line, coalesce(keyed.doc_id > firsts.first_id, false) AS dropped
  FROM keyed LEFT JOIN firsts ON keyed.k = firsts.k)
SELECT doc_id, count(*) AS n_lines, CAST(sum(CASE WHEN dropped THEN 1 ELSE 0 END) AS BIGINT) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT dropped), '')) AS kept_sha256
FROM judged GROUP BY doc_id
"""
