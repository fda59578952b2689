"""Degree-aware summation: low-degree vertices in one pass, hubs in two."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import RankConfig


def low_path(shares: DataFrame) -> DataFrame:
    """One aggregate by target; map-side sums come first."""
    return shares.groupBy(F.col("dst").alias("v")).agg(F.sum("share").alias("total"))


def high_path(shares: DataFrame, salts: int) -> DataFrame:
    """Two aggregates: salted partial sums, then one row per salt and hub."""
    part = shares.groupBy("dst", F.pmod(F.xxhash64("src"), F.lit(salts)).alias("salt")).agg(F.sum("share").alias("s"))
    return part.groupBy(F.col("dst").alias("v")).agg(F.sum("s").alias("total"))


def sending_edges(g, cfg: RankConfig) -> DataFrame:
    """The edges that a step sends along, with the classes of their ends where the layout asks for them."""
    return g.out_edges() if cfg.layout == "none" else g.classed_edges(cfg.split_degree)


def in_sums(shares: DataFrame, cfg: RankConfig) -> DataFrame:
    """(v, total) from (src, dst, share[, dst_hub]) under the configured layout; all layouts give the same sums."""
    if cfg.layout == "none":
        return low_path(shares)
    return low_path(shares.where(~F.col("dst_hub"))).unionByName(high_path(shares.where("dst_hub"), cfg.salts))


def expand_out(g, pending: DataFrame, cfg: RankConfig, few: bool) -> DataFrame:
    """(v): out-neighbours of the pending vertices.  Edges are never shuffled: a short frontier is sent to them.

    With layout ``both`` the edges of hubs are marked apart, and their targets combined before the shuffle.
    """
    front = pending.select(F.col("v").alias("src"))
    front = F.broadcast(front) if few else front
    mark = lambda e: e.join(front, "src", "left_semi").select(F.col("dst").alias("v"))
    if cfg.layout != "both":
        return mark(g.out_edges()).distinct()
    edges = g.classed_edges(cfg.split_degree)
    return mark(edges.where(~F.col("src_hub"))).unionByName(mark(edges.where("src_hub")).distinct()).distinct()
