"""Connected components of an edge table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise, release


def _smallest(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("u").agg(F.min("v").alias("m"))


def connected_components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(v, component) for every vertex of the edges (a, b); component is the smallest reachable id.

    Each half-round replaces edges by edges to the smallest neighbour; hubs are
    handled by an aggregate and a join, never by gathering a neighbourhood.
    The number of rounds is logarithmic in practice; the table is written to the
    shared folder each round, so the plan stays short.
    """
    now = materialise(edges.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    mark = None
    for _ in range(most_rounds):
        # Large star: larger neighbours of u hang on the smallest neighbour of u.
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = _smallest(both).select("u", F.least("u", "m").alias("m"))
        large = both.where(F.col("v") > F.col("u")).join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        # Small star: smaller neighbours of u, and u itself, hang on the smallest of them.
        small = large.join(_smallest(large), "u")
        last, now = now, materialise(
            small.where(F.col("v") != F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v"))
            .unionByName(small.select("u", F.col("m").alias("v")))
            .where(F.col("u") != F.col("v")).distinct()
        )
        release(last)
        seen = now.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v")), F.coalesce(F.sum(F.pmod(F.xxhash64("v", "u"), F.lit(1 << 20))), F.lit(0))).first()
        if seen == mark:
            break
        mark = seen
    else:
        raise RuntimeError("components did not settle")
    return now.groupBy(F.col("u").alias("v")).agg(F.min("v").alias("component")).unionByName(now.select(F.col("v"), F.col("v").alias("component")).distinct())
