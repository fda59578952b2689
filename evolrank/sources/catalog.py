"""Graphs carried by the star-schema, event, page and document tables.

Each function returns temporal edges (src, dst, ts) or static edges (src, dst).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SUPPLIER_SHIFT = 1_000_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def part_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part -> next part that the same customer ordered."""
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey", "l_linenumber", "l_partkey")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    moved = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(
        F.col("l_partkey").alias("src"), F.lead("l_partkey").over(w).alias("dst"), F.lead("o_orderdate").over(w).alias("ts")
    )
    return moved.where("dst IS NOT NULL")


def cust_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer -> supplier; supplier keys are shifted out of the customers' range."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(
        F.col("o_custkey").alias("src"), (F.col("l_suppkey") + SUPPLIER_SHIFT).alias("dst"), F.col("o_orderdate").alias("ts")
    )


def user_relay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User of one event -> user of the next in time.

    Hours are ordered side by side; the last event of an hour is followed by the first of the next hour that has one.
    """
    events = table(spark, sf_dir, "events").select("user_id", "ts", "event_id")
    hour = F.unix_date(F.to_date("ts")).cast("long") * 24 + F.hour("ts")
    cut = events.withColumn("slice", F.coalesce(hour, F.lit(-(2**62))))  # events without a time come first
    w = Window.partitionBy("slice").orderBy("ts", "event_id")
    after = F.lead(F.struct("user_id", "ts")).over(w)
    first = cut.groupBy("slice").agg(F.min(F.struct("ts", "event_id", "user_id")).alias("f"))
    follow = first.select("slice", F.lead(F.struct("f.user_id", "f.ts")).over(Window.orderBy("slice")).alias("beyond"))
    moved = cut.select("slice", F.col("user_id").alias("src"), after.alias("to")).join(F.broadcast(follow), "slice")
    then = F.coalesce("to", "beyond")
    return moved.select("src", then["user_id"].alias("dst"), then["ts"].alias("ts")).where("dst IS NOT NULL")


def state_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per user: state of one event -> state of the next."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    state = F.concat_ws(":", "event_type", F.get_json_object("props", "$.k"))
    events = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", state.alias("state"))
    return events.select(F.col("state").alias("src"), F.lead("state").over(w).alias("dst"), F.lead("ts").over(w).alias("ts")).where("dst IS NOT NULL")


def site_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page -> target of each link, fragments left out."""
    pages = table(spark, sf_dir, "pages")
    links = F.expr(r"regexp_extract_all(html, 'href=\"([^\"#]+)', 1)")
    return pages.select(F.col("url").alias("src"), F.explode(links).alias("dst"))


def word_kmer(spark: SparkSession, sf_dir: str, k: int = 3) -> DataFrame:
    """Shingle -> next shingle of a document."""
    words = F.split(F.lower("text"), "[ \t\r\n]+")
    docs = table(spark, sf_dir, "documents").select("doc_id", F.filter(words, lambda w: w != "").alias("w")).where(F.size("w") > k)
    run = lambda at: F.concat_ws(" ", *[F.get("w", at + i) for i in range(k)])
    spread = docs.select("w", F.explode(F.sequence(F.lit(0), F.size("w") - k - 1)).alias("p"))
    return spread.select(run(F.col("p")).alias("src"), run(F.col("p") + 1).alias("dst"))


def order_road(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order <-> next order of the customer and of the nation: low degree, long paths."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    both = orders.join(customers, F.col("o_custkey") == F.col("c_custkey"))
    follow = lambda key: F.lead("o_orderkey").over(Window.partitionBy(key).orderBy("o_orderdate", "o_orderkey"))
    pairs = both.select(F.col("o_orderkey").alias("a"), follow("o_custkey").alias("b")).unionByName(both.select(F.col("o_orderkey").alias("a"), follow("c_nationkey").alias("b"))).where("b IS NOT NULL")
    return pairs.select(F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(pairs.select(F.col("b").alias("src"), F.col("a").alias("dst")))


def part_supp_sym(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part <-> supplier."""
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("a"), (F.col("l_suppkey") + SUPPLIER_SHIFT).alias("b"))
    return lines.select(F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(lines.select(F.col("b").alias("src"), F.col("a").alias("dst")))


GRAPHS = {
    "part_flow": part_flow, "cust_supp": cust_supp, "user_relay": user_relay, "state_flow": state_flow,
    "site_links": site_links, "word_kmer3": word_kmer, "order_road": order_road, "part_supp_sym": part_supp_sym,
}
FAMILY = {
    "part_flow": "temporal", "cust_supp": "temporal", "user_relay": "temporal", "state_flow": "temporal",
    "site_links": "web", "word_kmer3": "kmer", "order_road": "road", "part_supp_sym": "social",
}
