"""Relational operators around the rankings: joins, aggregates, windows, sets, top-k."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import graph as G
from ..sources import catalog
from .queries import _PF, query

_t = catalog.table


def _flow(spark, sf):
    return G.static_edges(catalog.part_flow(spark, sf))


query("scan_parquet", "SELECT p_partkey, p_brand FROM part WHERE p_size > 25")(lambda spark, sf: _t(spark, sf, "part").where("p_size > 25").select("p_partkey", "p_brand"))
query("filter_edges", _PF + "SELECT src, dst FROM plain WHERE src BETWEEN 10 AND 50 AND dst IN (1, 2, 3, 5, 8, 13)")(lambda spark, sf: _flow(spark, sf).where("src BETWEEN 10 AND 50 AND dst IN (1, 2, 3, 5, 8, 13)"))
query("filter_distinct", _PF + "SELECT DISTINCT src FROM plain")(lambda spark, sf: _flow(spark, sf).select("src").distinct())
query("sample_edges", _PF + "SELECT src, dst FROM plain WHERE substr(md5(src || '|' || dst), 1, 1) = '0'")(lambda spark, sf: _flow(spark, sf).where(F.substring(F.md5(F.concat_ws("|", "src", "dst")), 1, 1) == "0"))
query("join_semi_active", _PF + "SELECT src, dst FROM plain WHERE dst IN (SELECT p_partkey FROM part WHERE p_size = 7)")(
    lambda spark, sf: _flow(spark, sf).join(_t(spark, sf, "part").where("p_size = 7").select(F.col("p_partkey").alias("dst")), "dst", "left_semi").select("src", "dst"))
query("join_anti_deadends", _PF + "SELECT src, dst FROM plain WHERE dst NOT IN (SELECT p_partkey FROM part WHERE p_size < 40)")(
    lambda spark, sf: _flow(spark, sf).join(_t(spark, sf, "part").where("p_size < 40").select(F.col("p_partkey").alias("dst")), "dst", "left_anti").select("src", "dst"))
query("join_merge_ranks", _PF + "SELECT src, dst, out_deg FROM plain JOIN deg ON v = src")(
    lambda spark, sf: (lambda e: e.hint("merge").join(G.degrees(G.with_self_loops(e)).select(F.col("v").alias("src"), "out_deg"), "src").select("src", "dst", "out_deg"))(_flow(spark, sf)))
query("join_shuffle_hash", _PF + "SELECT p_brand, count(*) AS n FROM plain JOIN part ON p_partkey = dst GROUP BY p_brand")(
    lambda spark, sf: _flow(spark, sf).join(_t(spark, sf, "part").hint("shuffle_hash").select(F.col("p_partkey").alias("dst"), "p_brand"), "dst").groupBy("p_brand").agg(F.count("*").alias("n")))
query("join_range_bins", "SELECT b.lo, count(*) AS n FROM part JOIN (VALUES (0, 10), (10, 30), (30, 60)) b(lo, hi) ON p_size >= lo AND p_size < hi GROUP BY b.lo")(
    lambda spark, sf: _t(spark, sf, "part").join(F.broadcast(spark.createDataFrame([(0, 10), (10, 30), (30, 60)], "lo int, hi int")), F.expr("p_size >= lo AND p_size < hi")).groupBy("lo").agg(F.count("*").alias("n")))
query("join_asof_batch", """SELECT e.event_id, max(b.k) AS batch FROM events e JOIN (SELECT k, TIMESTAMP '2024-01-01 00:00:00' + k * INTERVAL 1 DAY AS at FROM range(0, 31) r(k)) b ON b.at <= e.ts GROUP BY e.event_id""")(
    lambda spark, sf: _t(spark, sf, "events").where(F.col("ts") >= F.lit("2024-01-01").cast("timestamp_ntz")).select("event_id", F.least(F.lit(30), F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date"))).cast("long").alias("batch")))
query("agg_distinct_targets", _PF + "SELECT src, count(DISTINCT dst) AS targets FROM raw GROUP BY src")(lambda spark, sf: catalog.part_flow(spark, sf).groupBy("src").agg(F.countDistinct("dst").alias("targets")))
query("agg_in_contrib", _PF + "SELECT e.dst AS v, round(sum(1.0 / out_deg), 9) AS total FROM edges e JOIN deg ON deg.v = e.src GROUP BY e.dst")(
    lambda spark, sf: (lambda e: e.join(G.degrees(e).select(F.col("v").alias("src"), "out_deg"), "src").groupBy(F.col("dst").alias("v")).agg(F.round(F.sum(1.0 / F.col("out_deg")), 9).alias("total")))(G.with_self_loops(_flow(spark, sf))))
query("agg_rollup_geo", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")(
    lambda spark, sf: _t(spark, sf, "customer").join(_t(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(_t(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n")))
query("agg_cube_part", "SELECT p_brand, p_size, count(*) AS n FROM part GROUP BY CUBE (p_brand, p_size)")(lambda spark, sf: _t(spark, sf, "part").cube("p_brand", "p_size").agg(F.count("*").alias("n")))
query("agg_filtered", "SELECT event_type, count(*) FILTER (WHERE user_id % 2 = 0) AS even_users, count(*) AS n FROM events GROUP BY event_type")(
    lambda spark, sf: _t(spark, sf, "events").groupBy("event_type").agg(F.count(F.when(F.col("user_id") % 2 == 0, 1)).alias("even_users"), F.count("*").alias("n")))
query("agg_max_by", "SELECT o_custkey, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS best FROM orders GROUP BY o_custkey")(
    lambda spark, sf: _t(spark, sf, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("best")))
query("win_ranking", _PF + ", d AS (SELECT dst AS v, count(*) AS c FROM plain GROUP BY dst) SELECT v, c, rank() OVER (ORDER BY c DESC) AS rk, dense_rank() OVER (ORDER BY c DESC) AS dr FROM d")(
    lambda spark, sf: _flow(spark, sf).groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("c")).select("v", "c", F.rank().over(Window.orderBy(F.desc("c"))).cast("long").alias("rk"), F.dense_rank().over(Window.orderBy(F.desc("c"))).cast("long").alias("dr")))
query("topk_vertices", _PF + "SELECT dst AS v, count(*) AS c FROM plain GROUP BY dst ORDER BY c DESC, v LIMIT 20")(
    lambda spark, sf: _flow(spark, sf).groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("c")).orderBy(F.desc("c"), "v").limit(20))
query("topk_per_brand", _PF + ", d AS (SELECT dst AS v, count(*) AS c FROM plain GROUP BY dst) SELECT p_brand, v, c FROM d JOIN part ON p_partkey = v QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY c DESC, v) <= 3")(
    lambda spark, sf: _flow(spark, sf).groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("c")).join(_t(spark, sf, "part").select(F.col("p_partkey").alias("v"), "p_brand"), "v").withColumn("k", F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("c"), "v"))).where("k <= 3").select("p_brand", "v", "c"))
query("set_intersect", _PF + "SELECT src, dst FROM plain INTERSECT SELECT dst, src FROM plain")(lambda spark, sf: (lambda e: e.intersect(G.transpose(e)))(_flow(spark, sf)))
query("set_except", _PF + "SELECT src, dst FROM plain EXCEPT SELECT dst, src FROM plain")(lambda spark, sf: (lambda e: e.exceptAll(e.intersect(G.transpose(e))))(_flow(spark, sf)))
query("win_tumbling_batches", "SELECT date_trunc('day', ts) AS day, count(*) AS n FROM events GROUP BY 1")(lambda spark, sf: _t(spark, sf, "events").groupBy(F.date_trunc("day", "ts").alias("day")).agg(F.count("*").alias("n")))
query("fn_json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")(
    lambda spark, sf: _t(spark, sf, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))
query("agg_grouping_sets", "SELECT p_brand, p_size, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_size), ())")(
    lambda spark, sf: _t(spark, sf, "part").groupingSets([[F.col("p_brand")], [F.col("p_size")], []], "p_brand", "p_size").agg(F.count("*").alias("n")))
query("join_outer_degrees", _PF + ", o AS (SELECT src AS v, count(*) AS outs FROM plain GROUP BY src), i AS (SELECT dst AS v, count(*) AS ins FROM plain GROUP BY dst) SELECT v, coalesce(outs, 0) AS outs, coalesce(ins, 0) AS ins FROM o FULL JOIN i USING (v)")(
    lambda spark, sf: (lambda e: e.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("outs")).join(e.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("ins")), "v", "full").select("v", F.coalesce("outs", F.lit(0)).cast("long").alias("outs"), F.coalesce("ins", F.lit(0)).cast("long").alias("ins")))(_flow(spark, sf)))
query("set_union", _PF + "SELECT src, dst FROM plain UNION SELECT dst, src FROM plain")(lambda spark, sf: (lambda e: e.select("src", "dst").union(e.select("dst", "src")).distinct())(_flow(spark, sf)))
query("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 5")(lambda spark, sf: _t(spark, sf, "orders").select("o_orderkey").orderBy("o_orderkey").offset(5).limit(10))
query("win_last_value", "SELECT event_id, last_value(CASE WHEN value > 50 THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS last_large FROM events")(
    lambda spark, sf: _t(spark, sf, "events").select("event_id", F.last(F.when(F.col("value") > 50, F.col("event_id")), True).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)).alias("last_large")))
