"""Sources, functions, UDFs, windows and streams around the rankings."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.user_functions import NeighbourPairs, block_sums, euclidean, relative_change
from ..operators import graph as G
from ..sources import catalog
from ..sources.matrix_text import MatrixText
from ..storage import ensure_checkpoint_dir
from ..streaming import feeds
from .batches import temporal_slices
from .queries import _PF, query
from .relational import _flow, _t


def _folder(spark) -> str:
    ensure_checkpoint_dir(spark)
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return f"{str(base).rstrip('/')}/evolrank-io-{uuid.uuid4().hex}"


# ---- sources and sinks -------------------------------------------------------------------------------------------

EDGE = "src long, dst long"


@query("source_csv_edges", _PF + "SELECT src, dst FROM plain")
def _csv(spark, sf):
    path = _folder(spark)
    _flow(spark, sf).select("src", "dst").write.option("sep", " ").csv(path)
    return spark.read.schema(EDGE).option("sep", " ").option("comment", "#").csv(path)


@query("source_json_edges", _PF + "SELECT src, dst FROM plain")
def _json(spark, sf):
    path = _folder(spark)
    _flow(spark, sf).select("src", "dst").write.json(path)
    return spark.read.schema(EDGE).json(path)


@query("source_matrix_text", _PF + "SELECT src, dst FROM plain")
def _matrix(spark, sf):
    path = _folder(spark)
    _flow(spark, sf).select(F.concat_ws(" ", "src", "dst")).write.text(path)
    spark.dataSource.register(MatrixText)
    return spark.read.format("matrix_text").option("path", path).load()


@query("scan_snapshot_version", _PF + "SELECT src, dst FROM plain WHERE src % 4 = 1")
def _snapshot(spark, sf):
    path = _folder(spark)
    _flow(spark, sf).select("src", "dst", (F.col("src") % 4).alias("version")).write.partitionBy("version").parquet(path)
    return spark.read.parquet(path).where("version = 1").select("src", "dst")


@query("source_schema_check", "SELECT * FROM (VALUES ('dst', 'bigint', 'bigint', true), ('src', 'bigint', 'bigint', true), ('ts', 'string', 'timestamp', false)) t(field, inferred, wanted, same)")
def _schema(spark, sf):
    """Types that the JSON reader infers beside those that a feed of edges must have."""
    path = _folder(spark)
    _flow(spark, sf).limit(1000).select("src", "dst", F.lit("2024-01-01 00:00:00").alias("ts")).write.json(path)
    inferred = {f.name: f.dataType.simpleString() for f in spark.read.json(path).schema}
    wanted = {"src": "bigint", "dst": "bigint", "ts": "timestamp"}
    rows = [(k, inferred.get(k), wanted.get(k), inferred.get(k) == wanted.get(k)) for k in sorted({*inferred, *wanted})]
    return spark.createDataFrame(rows, "field string, inferred string, wanted string, same boolean")


# ---- projections and joins ---------------------------------------------------------------------------------------

query("proj_contribution", _PF + "SELECT v, round(CAST(0.85 AS DOUBLE) / out_deg, 9) AS share FROM deg")(
    lambda spark, sf: G.degrees(G.with_self_loops(_flow(spark, sf))).select("v", F.round(0.85 / F.col("out_deg"), 9).alias("share")))
query("join_broadcast_frontier", _PF + "SELECT DISTINCT dst AS v FROM plain WHERE src < 20")(
    lambda spark, sf: _flow(spark, sf).join(F.broadcast(spark.range(20).withColumnRenamed("id", "src")), "src", "left_semi").select(F.col("dst").alias("v")).distinct())
query("join_theta", "SELECT a.s_suppkey AS richer, b.s_suppkey AS poorer FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal > b.s_acctbal + 5000")(
    lambda spark, sf: (lambda s: s.select("s_nationkey", F.col("s_suppkey").alias("richer"), F.col("s_acctbal").alias("x")).join(
        s.select("s_nationkey", F.col("s_suppkey").alias("poorer"), F.col("s_acctbal").alias("y")), "s_nationkey").where("x > y + 5000").select("richer", "poorer"))(_t(spark, sf, "supplier")))


query("join_cross_n", _PF + "SELECT v, round(out_deg / CAST(n AS DOUBLE), 9) AS share FROM deg CROSS JOIN num")(
    lambda spark, sf: (lambda d: d.crossJoin(F.broadcast(d.agg(F.count("*").alias("n")))).select("v", F.round(F.col("out_deg") / F.col("n"), 9).alias("share")))(G.degrees(G.with_self_loops(_flow(spark, sf)))))


@query("join_interval", "SELECT a.event_id AS first_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _interval(spark, sf):
    """Events of one user within an hour: hour buckets are join keys, so a busy user is split by time."""
    e = _t(spark, sf, "events").select("user_id", "event_id", "ts", F.date_trunc("hour", "ts").alias("bucket"))
    left = e.select("user_id", F.col("event_id").alias("first_id"), F.col("ts").alias("t0"), F.explode(F.array("bucket", F.col("bucket") + F.expr("INTERVAL 1 HOUR"))).alias("bucket"))
    right = e.select("user_id", "bucket", F.col("event_id").alias("next_id"), F.col("ts").alias("t1"))
    return left.join(right, ["user_id", "bucket"]).where("t1 > t0 AND t1 <= t0 + INTERVAL 1 HOUR").select("first_id", "next_id")


# ---- aggregates and windows ---------------------------------------------------------------------------------------

query("agg_rank_percentiles", "SELECT p_brand, round(quantile_cont(p_retailprice, 0.5), 6) AS middle FROM part GROUP BY p_brand")(
    lambda spark, sf: _t(spark, sf, "part").groupBy("p_brand").agg(F.round(F.percentile("p_retailprice", 0.5), 6).alias("middle")))
query("agg_pivot", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS n_f, count(*) FILTER (WHERE o_orderstatus = 'O') AS n_o FROM orders GROUP BY o_orderpriority")(
    lambda spark, sf: _t(spark, sf, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).count().select("o_orderpriority", F.coalesce("F", F.lit(0)).alias("n_f"), F.coalesce("O", F.lit(0)).alias("n_o")))
query("win_cumulative_mass", "SELECT p_partkey, round(sum(p_retailprice) OVER (PARTITION BY p_brand ORDER BY p_partkey ROWS UNBOUNDED PRECEDING), 3) AS mass FROM part")(
    lambda spark, sf: _t(spark, sf, "part").select("p_partkey", F.round(F.sum("p_retailprice").over(Window.partitionBy("p_brand").orderBy("p_partkey").rowsBetween(Window.unboundedPreceding, 0)), 3).alias("mass")))
_RANGE = "count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL '1' DAY PRECEDING AND CURRENT ROW)"
query("win_time_range", f"SELECT event_id, {_RANGE} AS recent FROM events")(lambda spark, sf: _t(spark, sf, "events").select("event_id", F.expr(_RANGE).alias("recent")))
query("win_sliding", "SELECT CAST(CAST(date_trunc('day', ts) AS DATE) - CAST(k AS INTEGER) AS VARCHAR)[1:10] AS day, count(*) AS n FROM events, range(0, 2) r(k) GROUP BY 1")(
    lambda spark, sf: _t(spark, sf, "events").groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n")).select(F.col("window.start").cast("date").cast("string").alias("day"), "n"))
query("win_session", """WITH g AS (SELECT user_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh, ts FROM events),
s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, CAST(k AS BIGINT) AS k, count(*) AS n FROM s GROUP BY user_id, k""")(
    lambda spark, sf: _t(spark, sf, "events").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.row_number().over(Window.partitionBy("user_id").orderBy("w.start")).cast("long").alias("k"), "n"))


@query("win_rank_shift", _PF + """, t AS (SELECT src, dst, row_number() OVER (ORDER BY ts, src, dst) - 1 AS k, count(*) OVER () AS c FROM raw),
a AS (SELECT dst AS v, rank() OVER (ORDER BY count(DISTINCT src) DESC) AS r FROM t WHERE k < CAST(floor(0.9 * c) AS BIGINT) GROUP BY dst),
b AS (SELECT dst AS v, rank() OVER (ORDER BY count(DISTINCT src) DESC) AS r FROM t GROUP BY dst)
SELECT v, CAST(a.r - b.r AS BIGINT) AS shift FROM a JOIN b USING (v)""")
def _shift(spark, sf):
    """Places that a vertex gained by in-degree between the preloaded and the whole graph."""
    flow = catalog.part_flow(spark, sf)
    placed = lambda e, name: e.groupBy(F.col("dst").alias("v")).agg(F.countDistinct("src").alias("c")).select("v", F.rank().over(Window.orderBy(F.desc("c"))).alias(name))
    return placed(temporal_slices(flow, 1e-3, 1)[0], "r0").join(placed(flow, "r1"), "v").select("v", (F.col("r0") - F.col("r1")).cast("long").alias("shift"))


# ---- functions -----------------------------------------------------------------------------------------------------

query("fn_string_links", "SELECT page_id, CAST(len(regexp_extract_all(html, 'href=\"([^\"#]+)', 1)) AS BIGINT) AS links, lower(url) AS url FROM pages")(
    lambda spark, sf: _t(spark, sf, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="([^"#]+)'), F.lit(1))).cast("long").alias("links"), F.lower("url").alias("url")))
query("fn_date_batches", "SELECT strftime(o_orderdate, '%Y-%m-01') AS month, max(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))) AS last_day, count(*) AS n FROM orders GROUP BY 1")(
    lambda spark, sf: _t(spark, sf, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM-01").alias("month")).agg(F.max(F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date"))).cast("long").alias("last_day"), F.count("*").alias("n")))
query("fn_math_norms", "SELECT p_brand, round(sqrt(sum(p_retailprice * p_retailprice)), 4) AS l2, round(max(abs(p_retailprice)), 4) AS linf, round(ln(sum(p_size)), 6) AS size_log FROM part GROUP BY p_brand")(
    lambda spark, sf: _t(spark, sf, "part").groupBy("p_brand").agg(F.round(F.sqrt(F.sum(F.col("p_retailprice") * F.col("p_retailprice"))), 4).alias("l2"), F.round(F.max(F.abs("p_retailprice")), 4).alias("linf"), F.round(F.log(F.sum("p_size")), 6).alias("size_log")))
query("fn_array_adjacency", _PF + "SELECT src AS v, len(list(dst)) AS n, array_to_string(list_slice(list_sort(list(dst)), 1, 3), ',') AS head FROM plain GROUP BY src")(
    lambda spark, sf: G.packed_adjacency(_flow(spark, sf)).groupBy("v").agg(F.sum(F.size("nbrs")).cast("long").alias("n"), F.array_join(F.slice(F.sort_array(F.flatten(F.collect_list(F.slice("nbrs", 1, 3)))), 1, 3), ",").alias("head")))
query("fn_map_degree", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")(
    lambda spark, sf: _t(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("c")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "c"))).alias("m"))
    .select("user_id", F.coalesce(F.element_at("m", F.lit("click")), F.lit(0)).cast("long").alias("clicks"), F.size("m").cast("long").alias("kinds")))

# ---- user functions and SQL ------------------------------------------------------------------------------------------

query("udf_relative_change", "SELECT p_partkey, round(abs(p_retailprice - p_size) / greatest(p_retailprice, p_size), 9) AS change FROM part")(
    lambda spark, sf: _t(spark, sf, "part").select("p_partkey", F.round(relative_change(F.col("p_retailprice"), F.col("p_size").cast("double")), 9).alias("change")))
query("udaf_l2", "SELECT p_brand, round(sqrt(sum(p_retailprice * p_retailprice)), 4) AS l2 FROM part GROUP BY p_brand")(
    lambda spark, sf: _t(spark, sf, "part").groupBy("p_brand").agg(F.round(euclidean("p_retailprice"), 4).alias("l2")))


@query("udf_block_kernel", _PF + "SELECT dst AS v, round(sum(CAST(1.0 AS DOUBLE) / out_deg), 9) AS total FROM edges JOIN deg ON deg.v = src GROUP BY dst")
def _kernel(spark, sf):
    """In-contributions summed block by block in Python; a block is an Arrow batch, so a hub never fills one."""
    edges = G.with_self_loops(_flow(spark, sf))
    rows = edges.join(G.degrees(edges).select(F.col("v").alias("src"), "out_deg"), "src").select(F.col("dst").alias("v"), "out_deg")
    part = rows.mapInPandas(block_sums, "v long, total double")
    return part.groupBy("v").agg(F.round(F.sum("total"), 9).alias("total"))


@query("udtf_shingles", "SELECT p_partkey, w[i] || ' ' || w[i + 1] AS pair FROM (SELECT p_partkey, w, unnest(range(1, len(w))) AS i FROM (SELECT p_partkey, string_split(p_name, ' ') AS w FROM part))")
def _pairs(spark, sf):
    spark.udtf.register("neighbour_pairs", F.udtf(NeighbourPairs, returnType="pair string"))
    return spark.sql("SELECT p_partkey, s.pair FROM {part}, LATERAL neighbour_pairs(p_name) s", part=_t(spark, sf, "part"))


query("sql_view_ranks", _PF + "SELECT src, count(*) AS outs FROM plain GROUP BY src HAVING count(*) > 20")(
    lambda spark, sf: spark.sql("SELECT src, count(*) AS outs FROM {edges} GROUP BY src HAVING count(*) > :least", args={"least": 20}, edges=_flow(spark, sf)))


@query("sql_recursive_depth", _PF.replace("WITH ", "WITH RECURSIVE ", 1) + ", walk(v, depth) AS (SELECT CAST(1 AS BIGINT), 0 UNION ALL SELECT dst, depth + 1 FROM walk JOIN plain ON src = v WHERE depth < 2) SELECT depth, count(*) AS walks FROM walk GROUP BY depth")
def _depth(spark, sf):
    _flow(spark, sf).createOrReplaceTempView("evolrank_flow")
    return spark.sql("WITH RECURSIVE walk(v, depth) AS (SELECT CAST(1 AS BIGINT), 0 UNION ALL SELECT dst, depth + 1 FROM walk JOIN evolrank_flow ON src = v WHERE depth < 2) SELECT depth, count(*) AS walks FROM walk GROUP BY depth")


# ---- streams ----------------------------------------------------------------------------------------------------------


@query("stream_edge_count", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def _stream(spark, sf):
    """Events read as a stream; each micro-batch leaves its partial counts as one version."""
    path, schema = _folder(spark), _t(spark, sf, "events").schema
    stream = feeds.event_stream(spark, f"{sf}/events.parque[t]", schema)
    feeds.maintain(stream, f"{path}/out", f"{path}/state", lambda b: b.groupBy("user_id").agg(F.count("*").alias("n")))
    return spark.read.parquet(f"{path}/out/version=*").groupBy("user_id").agg(F.sum("n").cast("long").alias("n"))
