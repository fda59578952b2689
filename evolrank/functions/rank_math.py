"""Rank equations, norms and measures as column expressions and small plans."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import RankConfig


def plain_update(total: Column, cfg: RankConfig, n: int) -> Column:
    """Teleport share plus damped in-contributions."""
    return F.lit((1.0 - cfg.alpha) / n) + cfg.alpha * F.coalesce(total, F.lit(0.0))


def looped_update(total: Column, rank: Column, out_deg: Column, cfg: RankConfig, n: int) -> Column:
    """The same equation solved for a vertex's own rank, its loop taken out of the sum."""
    others = F.coalesce(total, F.lit(0.0)) - rank / out_deg
    return (cfg.alpha * others + (1.0 - cfg.alpha) / n) / (1.0 - cfg.alpha / out_deg)


def relative_change(a: Column, b: Column) -> Column:
    return F.abs(a - b) / F.greatest(a, b)


def vector_norm(pairs: DataFrame, a: str, b: str, norm: str) -> Column:
    d = F.abs(F.col(a) - F.col(b))
    return {"linf": F.max(d), "l1": F.sum(d), "l2": F.sqrt(F.sum(d * d))}[norm]


def rank_error(ranks: DataFrame, reference: DataFrame) -> DataFrame:
    """L1 distance of two rank tables (v, rank)."""
    both = ranks.select("v", F.col("rank").alias("x")).join(reference.select("v", F.col("rank").alias("y")), "v", "full")
    return both.agg(F.sum(F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0)))).alias("error"))


def geometric_mean(value: Column) -> Column:
    return F.exp(F.avg(F.log(value)))


def speedups(rows: DataFrame) -> DataFrame:
    """(approach, base, speedup, seconds, visit_ratio, work_ratio): each of the rows (approach, seconds, visits, work) against each, itself included.

    ``speedup`` is the time of the base over that of the approach; the other two compare edges in the same way.
    """
    base = rows.select(*(F.col(c).alias(f"base_{c}") for c in rows.columns))
    over = lambda c: F.col(f"base_{c}") / F.greatest(F.col(c), F.lit(1))
    return rows.crossJoin(F.broadcast(base)).select(
        "approach", F.col("base_approach").alias("base"), (F.col("base_seconds") / F.col("seconds")).alias("speedup"), "seconds", over("visits").alias("visit_ratio"), over("work").alias("work_ratio"))


def indirect_ratio(rows: DataFrame, bases: DataFrame) -> DataFrame:
    """(row_id, speedup): what each row (row_id, base_id, ratio) is to its base, times what the base (base_id, base) is to the common one."""
    return rows.join(bases, "base_id").select("row_id", F.round(F.col("ratio") * F.col("base"), 6).alias("speedup"))


def recommend(update_kind: str, batch_fraction: float, family: str = "", error_matters: bool = False) -> str:
    """Which approach to run: frontier with pruning, unless errors matter or random batches are large."""
    if error_matters or update_kind == "random" and batch_fraction > 1e-4:
        return "warm"
    return "grow_prune"


def recommend_column(update_kind: Column, batch_fraction: Column, error_matters: Column) -> Column:
    return F.when(error_matters | ((update_kind == "random") & (batch_fraction > 1e-4)), "warm").otherwise("grow_prune")


def rank_percentile(ranks: DataFrame, vertices: list, most: int = 1000) -> DataFrame:
    """(v, below): the share of all vertices ranked lower than each asked one, in one pass without a sort.

    ``vertices`` are at most ``most`` values named by the caller; those that have no rank give no row.
    """
    if len(vertices) > most:
        raise ValueError(f"at most {most} vertices can be asked at once")
    asked = ranks.where(F.col("v").isin(vertices)).select("v", "rank").collect()
    if not asked:
        return ranks.select("v", F.lit(0.0).alias("below")).limit(0)
    lower = F.array(*[F.avg((F.col("rank") < r.rank).cast("double")) for r in asked])
    return ranks.agg(lower.alias("shares")).select(F.posexplode("shares").alias("at", "share")).select(
        F.element_at(F.array(*[F.lit(r.v) for r in asked]), F.col("at") + 1).alias("v"), F.round("share", 9).alias("below"))
