"""Snapshots of a directed graph: construction, degrees, batches of changes."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import bucketed


@dataclass(frozen=True)
class Graph:
    """edges (src, dst), one loop a vertex; degrees (v, out_deg, in_deg).

    ``held`` keeps the copies of the edges that were dealt out by source or by
    target; they are made once a snapshot and shared by all approaches.
    """

    edges: DataFrame
    degrees: DataFrame
    n: int
    version: int = 0
    held: dict = field(default_factory=dict, compare=False, repr=False)

    @property
    def parts(self) -> int:
        return self.held.setdefault("parts", int(self.edges.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def size(self) -> int:
        """The number of edges, counted once."""
        if "size" not in self.held:
            self.held["size"] = self.edges.count()
        return self.held["size"]

    def out_edges(self) -> DataFrame:
        """(src, dst) dealt out by source: for sending along edges."""
        if "out" not in self.held:
            self.held["out"] = bucketed(self.edges.select("src", "dst"), "src", self.parts)
        return self.held["out"]

    def in_edges(self) -> DataFrame:
        """(src, dst) dealt out by target: for pulling to a few vertices."""
        if "in" not in self.held:
            self.held["in"] = bucketed(self.edges.select("src", "dst"), "dst", self.parts)
        return self.held["in"]

    def classed_edges(self, split_degree: int) -> DataFrame:
        """(src, dst, src_hub, dst_hub) dealt out by source: whether each end has at least so many edges."""
        key = ("classed", split_degree)
        if key not in self.held:
            ends = self.edges.join(self.degrees.select(F.col("v").alias("src"), (F.col("out_deg") >= split_degree).alias("src_hub")), "src")
            ends = ends.join(self.degrees.select(F.col("v").alias("dst"), (F.col("in_deg") >= split_degree).alias("dst_hub")), "dst")
            self.held[key] = bucketed(ends.select("src", "dst", "src_hub", "dst_hub"), "src", self.parts)
        return self.held[key]


def static_edges(temporal: DataFrame) -> DataFrame:
    """Distinct edges without loops and without null ends."""
    return temporal.select("src", "dst").where("src IS NOT NULL AND dst IS NOT NULL AND src <> dst").distinct()


def vertices(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("v")).union(edges.select("dst")).distinct()


def with_self_loops(edges: DataFrame) -> DataFrame:
    """Exactly one loop for every vertex: no dead ends are left."""
    plain = edges.where("src <> dst").select("src", "dst").distinct()
    return plain.unionByName(vertices(edges).select(F.col("v").alias("src"), F.col("v").alias("dst")))


def degrees(edges: DataFrame) -> DataFrame:
    both = edges.select(F.col("src").alias("v"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionByName(edges.select(F.col("dst").alias("v"), F.lit(0).alias("o"), F.lit(1).alias("i")))
    return both.groupBy("v").agg(F.sum("o").alias("out_deg"), F.sum("i").alias("in_deg"))


def build(temporal: DataFrame, version: int = 0) -> Graph:
    """A snapshot with loops from any edge table."""
    edges = with_self_loops(temporal)
    deg = degrees(edges)
    return Graph(edges, deg, deg.count(), version)


def transpose(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def dead_ends(edges: DataFrame) -> DataFrame:
    """Vertices without an out-edge (of a graph without loops)."""
    return vertices(edges).join(edges.select(F.col("src").alias("v")).distinct(), "v", "left_anti")


def packed_adjacency(edges: DataFrame, chunk: int = 1024) -> DataFrame:
    """(v, chunk, nbrs): sorted neighbour arrays of about ``chunk`` entries; a hub has as many rows as its degree asks for."""
    size = edges.groupBy("src").agg(F.ceil(F.count("*") / F.lit(chunk)).alias("slots"))
    slot = F.pmod(F.xxhash64("dst"), F.col("slots"))
    return edges.join(size, "src").groupBy(F.col("src").alias("v"), slot.alias("chunk")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))


def normalise_delta(edges: DataFrame, delta: DataFrame) -> DataFrame:
    """Drop what changes nothing: present insertions, absent deletions, pairs in both, loops."""
    asked = delta.where("src <> dst").select("op", "src", "dst").distinct()
    twice = asked.groupBy("src", "dst").agg(F.count("*").alias("c")).where("c > 1").select("src", "dst")
    once = asked.join(twice, ["src", "dst"], "left_anti")
    ins = once.where("op = 'ins'").join(edges.select("src", "dst"), ["src", "dst"], "left_anti")
    dels = once.where("op = 'del'").join(edges.select("src", "dst"), ["src", "dst"], "left_semi")
    return ins.unionByName(dels).select("op", "src", "dst")


def apply_delta(edges: DataFrame, delta: DataFrame) -> DataFrame:
    """Edges after a batch; loops are never deleted, new vertices get theirs."""
    gone = delta.where("op = 'del' AND src <> dst").select("src", "dst")
    new = delta.where("op = 'ins'").select("src", "dst")
    kept = edges.join(gone, ["src", "dst"], "left_anti").unionByName(new).distinct()
    loops = vertices(new).select(F.col("v").alias("src"), F.col("v").alias("dst"))
    return kept.unionByName(loops).distinct()


def changed_degrees(deg: DataFrame, edges: DataFrame, delta: DataFrame) -> DataFrame:
    """(v, out_deg, in_deg) after a batch on ``edges``: only the ends of real changes are counted anew."""
    real = normalise_delta(edges, delta).withColumn("by", F.when(F.col("op") == "ins", 1).otherwise(-1))
    ends = real.select(F.col("src").alias("v"), F.col("by").alias("o"), F.lit(0).alias("i")).unionByName(real.select(F.col("dst").alias("v"), F.lit(0).alias("o"), F.col("by").alias("i")))
    moved = ends.groupBy("v").agg(F.sum("o").alias("o"), F.sum("i").alias("i"))
    # A vertex that was not there before gets its loop, which counts once on each side.
    was = lambda c: F.coalesce(c, F.lit(1))
    return deg.join(moved, "v", "full").select("v", (was("out_deg") + F.coalesce("o", F.lit(0))).alias("out_deg"), (was("in_deg") + F.coalesce("i", F.lit(0))).alias("in_deg"))


def diff(old: DataFrame, new: DataFrame) -> DataFrame:
    """The batch that turns one edge table into another."""
    a, b = old.select("src", "dst"), new.select("src", "dst")
    return b.exceptAll(a).select(F.lit("ins").alias("op"), "src", "dst").unionByName(a.exceptAll(b).select(F.lit("del").alias("op"), "src", "dst"))


def describe(temporal: DataFrame) -> DataFrame:
    """One row: vertices, temporal edges, static edges, average degree with loops."""
    plain = static_edges(temporal)
    n = vertices(temporal.where("src IS NOT NULL AND dst IS NOT NULL")).agg(F.count("*").alias("n_vertices"))
    m = plain.agg(F.count("*").alias("n_edges"))
    t = temporal.agg(F.count("*").alias("n_temporal"))
    return n.crossJoin(t).crossJoin(m).select("n_vertices", "n_temporal", "n_edges", F.round((F.col("n_edges") + F.col("n_vertices")) / F.col("n_vertices"), 6).alias("avg_degree"))


def degree_split(deg: DataFrame, side: str = "in_deg", split_degree: int = 64, buckets: int = 64) -> DataFrame:
    """(v, klass, pos): low degrees first, each class in key order.

    Positions come from counts per key range and class and a prefix sum over that small
    table, never from a window over all vertices.
    """
    klass = F.when(F.col(side) < split_degree, "low").otherwise("high")
    ranged = deg.select("v", klass.alias("klass")).repartitionByRange(buckets, "v").sortWithinPartitions("v")
    from ..storage import settle

    # The second step needs the same ranges as the first.
    parted = settle(ranged.withColumn("part", F.spark_partition_id()))
    from pyspark.sql import Window

    counts = parted.groupBy("klass", "part").agg(F.count("*").alias("c"))
    before = counts.withColumn("base", F.sum("c").over(Window.orderBy(F.when(F.col("klass") == "low", 0).otherwise(1), "part").rowsBetween(Window.unboundedPreceding, -1)))
    inner = F.row_number().over(Window.partitionBy("klass", "part").orderBy("v")) - 1
    return parted.withColumn("at", inner).join(F.broadcast(before.drop("c")), ["klass", "part"]).select("v", "klass", (F.col("at") + F.coalesce("base", F.lit(0))).cast("long").alias("pos"))
