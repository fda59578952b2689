"""Streams, sources and user functions."""

from __future__ import annotations

from pyspark.sql import functions as F

from evolrank.plans import surface  # noqa: F401
from evolrank.plans.queries import QUERIES
from evolrank.sources.matrix_text import MatrixText
from evolrank.streaming import feeds

SF = "/root/testdata/sf0.001"


def test_stream_equals_batch(spark):
    want = {r.user_id: r["count"] for r in spark.read.parquet(f"{SF}/events.parquet").groupBy("user_id").count().collect()}
    assert {r.user_id: r.n for r in QUERIES["stream_edge_count"](spark, SF).collect()} == want


def test_a_version_is_written_once(spark, tmp_path):
    write = feeds.version_writer(str(tmp_path / "out"), lambda b: b)
    write(spark.range(3), 0)
    write(spark.range(9), 0)
    write(spark.range(5), 1)
    got = feeds.versions(spark, str(tmp_path / "out"), spark.range(1).schema).groupBy("version").count().collect()
    assert {r.version: r["count"] for r in got} == {0: 3, 1: 5}


def test_duplicates_go_within_the_watermark(spark, tmp_path):
    rows = spark.sql("SELECT 1L AS src, 2L AS dst, TIMESTAMP'2024-01-01 00:00:00' AS ts UNION ALL SELECT 1L, 2L, TIMESTAMP'2024-01-01 00:00:01' UNION ALL SELECT 2L, 1L, TIMESTAMP'2024-01-01 00:00:02'")
    rows.coalesce(1).write.parquet(str(tmp_path / "in"))
    once = feeds.without_late_duplicates(feeds.event_stream(spark, str(tmp_path / "in"), rows.schema))
    feeds.maintain(once, str(tmp_path / "out"), str(tmp_path / "state"), lambda b: b)
    assert spark.read.parquet(str(tmp_path / "out/version=0")).count() == 2


def test_matrix_text(spark, tmp_path):
    (tmp_path / "m.mtx").write_text("%%head\n% more\n3 3 2\n1 2\n3 1\n")
    spark.dataSource.register(MatrixText)
    got = spark.read.format("matrix_text").option("path", str(tmp_path / "m.mtx")).load()
    assert {tuple(r) for r in got.collect()} == {(1, 2), (3, 1)}


def test_snapshot_scan_prunes_folders(spark):
    assert QUERIES["scan_snapshot_version"](spark, SF).where(F.col("src") % 4 != 1).isEmpty()
