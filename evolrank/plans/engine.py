"""The iteration engine: five ranking approaches as loops over DataFrame steps.

Edges are dealt out by source and the state (rank and degrees) by vertex, once a
snapshot, as bucketed tables: a full step joins them without an exchange and
shuffles only partial sums to their targets.  No step ever shuffles edges.

A frontier of few vertices (counted) is worked on apart: the edges into its
vertices are read once from a copy dealt out by target, the ranks that they need
come along, and later steps touch these few rows only.  Changed ranks are held
beside the state and merged when the frontier grows beyond the bound.

Every step is written to the shared folder, so plans stay short and a lost
executor costs one step at most; what a step read is deleted after it.

Graphs that fit one task (``resident.MOST_EDGES``) run all their steps there.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import RankConfig
from ..functions.rank_math import looped_update, plain_update, relative_change
from ..operators import frontier
from ..operators.graph import Graph, apply_delta, changed_degrees
from ..operators.layouts import expand_out, in_sums, sending_edges
from ..storage import bucketed, discard, written
from . import resident


EDGES_A_VERTEX = 20  # in-edges of a small frontier, for each vertex that it may have
SMALL_SHARE = 8  # and an eighth of all edges at most: beyond that a full step costs less


@dataclass
class RankResult:
    ranks: DataFrame  # (v, rank, ever)
    iterations: int
    delta: float
    edge_visits: int
    log: list = field(default_factory=list)
    followed: int = 0  # out-edges that the marking of vertices went along; seeds are counted by ``frontier.seed_edges``

    def report(self) -> DataFrame:
        """(v, rank_r, iterations): the comparable form."""
        return self.ranks.select("v", F.round("rank", 9).alias("rank_r"), F.lit(self.iterations).cast("long").alias("iterations"))


def uniform(g: Graph) -> DataFrame:
    return g.degrees.select("v", F.lit(1.0 / g.n).alias("rank"))


def deal(g: Graph) -> Graph:
    """The same graph over its dealt copies: edges by source, degrees by vertex."""
    if "deg" not in g.held:
        g.held["deg"] = bucketed(g.degrees, "v", g.parts)
    return replace(g, edges=g.out_edges(), degrees=g.held["deg"])


def _state(g: Graph, ranks: DataFrame) -> DataFrame:
    """(v, rank, out_deg, in_deg)."""
    if "out_deg" in ranks.columns:
        return ranks.select("v", "rank", "out_deg", "in_deg")
    return ranks.select("v", "rank").join(g.degrees, "v")


def pull_step(g: Graph, ranks: DataFrame, cfg: RankConfig, active: DataFrame | None = None, looped: bool = False, few: bool = False) -> DataFrame:
    """(v, rank, prev, visits, out_deg, in_deg): one synchronous step; only ``active`` vertices (all if None) are recomputed.

    With ``few`` the active vertices are broadcast and only their sums are
    shuffled; without it all sums are, as in a step without ``active``.
    """
    state = _state(g, ranks)
    edges = sending_edges(g, cfg)
    if active is not None and few:
        edges = edges.join(F.broadcast(active.select(F.col("v").alias("dst"))), "dst", "left_semi")
    shares = state.select(F.col("v").alias("src"), (F.col("rank") / F.col("out_deg")).alias("share"))
    sums = in_sums(edges.join(shares, "src"), cfg)
    joined = state.select("v", F.col("rank").alias("prev"), "out_deg", "in_deg").join(sums, "v", "left")
    if active is None:
        joined = joined.withColumn("on", F.lit(True))
    else:
        marked = active.select("v", F.lit(True).alias("on"))
        joined = joined.join(F.broadcast(marked) if few else marked, "v", "left")
    new = looped_update(F.col("total"), F.col("prev"), F.col("out_deg"), cfg, g.n) if looped else plain_update(F.col("total"), cfg, g.n)
    return joined.select("v", F.when(F.col("on"), new).otherwise(F.col("prev")).alias("rank"), "prev", F.when(F.col("on"), F.col("in_deg")).otherwise(F.lit(0)).cast("long").alias("visits"), "out_deg", "in_deg")


def _measure(step: DataFrame, cfg: RankConfig, *sums: Column) -> tuple:
    """Norm of the change and in-edges read, then whatever ``sums`` count."""
    d = F.abs(F.col("rank") - F.col("prev"))
    norm = {"linf": F.max(d), "l1": F.sum(d), "l2": F.sqrt(F.sum(d * d))}[cfg.norm]
    change, *counts = step.agg(norm, F.sum("visits"), *sums).first()
    return float(change or 0.0), *(int(c or 0) for c in counts)


def _iterate(g: Graph, start: DataFrame, cfg: RankConfig) -> RankResult:
    """Full steps until the norm is small."""
    if resident.fits(g):
        return resident.run(g, start, resident.power(cfg, cfg.bar(g.n)))
    g = deal(g)
    state, visits, log, delta, i = bucketed(_state(g, start), "v", g.parts), 0, [], float("inf"), 0
    while i < cfg.max_iter and delta > cfg.bar(g.n):
        step = bucketed(pull_step(g, state, cfg), "v", g.parts)
        discard(state)
        i += 1
        delta, seen = _measure(step, cfg)
        visits += seen
        log.append((i, delta, seen))
        state = step
    return RankResult(state.select("v", "rank", F.lit(True).alias("ever")), i, delta, visits, log)


def static_rank(g: Graph, cfg: RankConfig = RankConfig()) -> RankResult:
    """Power iteration from the uniform vector."""
    return _iterate(g, uniform(g), cfg)


def carry_over(g: Graph, prev: DataFrame) -> DataFrame:
    """Previous ranks on the vertices of ``g``; new vertices start at the uniform share."""
    return g.degrees.select("v").join(prev.select("v", "rank"), "v", "left").select("v", F.coalesce("rank", F.lit(1.0 / g.n)).alias("rank"))


def warm_rank(g: Graph, prev: DataFrame, cfg: RankConfig = RankConfig()) -> RankResult:
    """All vertices, from the previous ranks."""
    return _iterate(g, carry_over(g, prev), cfg)


class _Local:
    """A frontier of few vertices: the edges into all it ever held, and the ranks that moved since the state was written.

    ``latest`` has one row for each vertex that was recomputed: (v, rank, prev, visits, out_deg), visits 0 if not in the last step.
    """

    def __init__(self, g: Graph, state: DataFrame, cfg: RankConfig):
        self.g, self.state, self.cfg = g, state, cfg
        self.near: list[DataFrame] = []  # (dst, src, was, out_deg)
        self.latest: DataFrame | None = None

    def _fetch(self, flags: DataFrame) -> None:
        """Read the in-edges of vertices that are flagged for the first time, with the ranks of their sources."""
        new = flags.select(F.col("v").alias("dst"))
        if self.near:  # every vertex has a loop, so it is a target of the edges that were read for it
            new = new.join(frontier.merge(self.near).select("dst").distinct(), "dst", "left_anti")
        rows = self.g.in_edges().join(F.broadcast(new), "dst", "left_semi")
        state = self.state.select(F.col("v").alias("src"), F.col("rank").alias("was"), "out_deg")
        self.near.append(written(state.join(F.broadcast(rows), "src").select("dst", "src", "was", "out_deg")))
        if len(self.near) > frontier.MOST_PARTS:
            parts, self.near = self.near, [written(frontier.merge(self.near))]
            discard(*parts)

    def step(self, flags: DataFrame, looped: bool) -> DataFrame:
        self._fetch(flags)
        near = frontier.merge(self.near).join(F.broadcast(flags.select(F.col("v").alias("dst"))), "dst", "left_semi")
        if self.latest is not None:
            near = near.join(F.broadcast(self.latest.select(F.col("v").alias("src"), F.col("rank").alias("now"))), "src", "left").withColumn("was", F.coalesce("now", "was"))
        loop = F.col("src") == F.col("dst")
        sums = near.groupBy(F.col("dst").alias("v")).agg(
            F.sum(F.col("was") / F.col("out_deg")).alias("total"), F.max(F.when(loop, F.col("was"))).alias("prev"),
            F.max(F.when(loop, F.col("out_deg"))).alias("out_deg"), F.count("*").alias("visits"),
        )
        new = looped_update(F.col("total"), F.col("prev"), F.col("out_deg"), self.cfg, self.g.n) if looped else plain_update(F.col("total"), self.cfg, self.g.n)
        made, last = sums.select("v", new.alias("rank"), "prev", "visits", "out_deg"), self.latest
        if last is not None:
            still = last.join(F.broadcast(flags.select("v")), "v", "left_anti")
            made = made.unionByName(still.select("v", "rank", F.col("rank").alias("prev"), F.lit(0).cast("long").alias("visits"), "out_deg"))
        self.latest = written(made)
        discard(last)
        return self.latest

    def merged(self) -> DataFrame:
        """The state with all ranks that moved."""
        if self.latest is None:
            return self.state
        moved = self.latest.select("v", F.col("rank").alias("now"))
        return self.state.join(moved, "v", "left").select("v", F.coalesce("now", "rank").alias("rank"), "out_deg", "in_deg")

    def drop(self) -> None:
        discard(*self.near, self.latest)


def _size(g: Graph, flags: DataFrame) -> tuple[int, int, int]:
    """Vertices of a frontier, their in-edges and their out-edges."""
    return tuple(g.degrees.join(flags, "v", "left_semi").agg(F.count("*"), *(F.coalesce(F.sum(c), F.lit(0)) for c in ("in_deg", "out_deg"))).first())


def _frontier_loop(g: Graph, start: DataFrame, flags: DataFrame, cfg: RankConfig, prune: bool = False, grow: bool = True) -> RankResult:
    """Steps over flagged vertices; ``flags`` (v) is a written table, fixed without ``grow``."""
    g = deal(g)
    state, local = bucketed(_state(g, start), "v", g.parts), None
    ever, visits, log, change, i = [flags], 0, [], float("inf"), 0
    n_flags, n_near, n_sent = _size(g, flags)
    followed = 0 if grow else n_sent  # a fixed frontier is all that was reached, each vertex expanded once
    spreads = (F.col("visits") > 0) & (relative_change(F.col("rank"), F.col("prev")) > cfg.tol_frontier)
    total = g.degrees.agg(F.sum("in_deg")).first()[0]
    if not n_flags:
        return RankResult(written(state.select("v", "rank", F.lit(False).alias("ever"))), 1, 0.0, 0, [(1, 0.0, 0)])
    while i < cfg.max_iter and change > cfg.bar(g.n) and n_flags:
        small = n_flags <= cfg.frontier_rows
        if small and n_near <= min(EDGES_A_VERTEX * cfg.frontier_rows, total // SMALL_SHARE):
            local = local or _Local(g, state, cfg)
            step = local.step(flags, prune)
        else:
            step = bucketed(pull_step(g, state if local is None else local.merged(), cfg, flags, prune, small), "v", g.parts)
            discard(state)
            if local is not None:
                local.drop()
            state, local = step, None
        i += 1
        change, seen, sent = _measure(step, cfg, F.sum(F.when(spreads, F.col("out_deg"))))
        visits += seen
        log.append((i, change, seen))
        if not grow or change <= cfg.bar(g.n):
            continue
        touched = step.where("visits > 0").withColumn("rel", relative_change(F.col("rank"), F.col("prev")))
        kept = touched.where(F.col("rel") > cfg.tol_prune).select("v") if prune else flags
        grown = expand_out(g, touched.where(F.col("rel") > cfg.tol_frontier), cfg, small)
        followed += sent
        flags = written(kept.unionByName(grown).distinct())
        n_flags, n_near, _ = _size(g, flags)
        ever.append(flags)
        if len(ever) > frontier.MOST_PARTS:
            parts, ever = ever, [written(frontier.merge(ever).distinct())]
            discard(*(p for p in parts if p is not flags))
    if not n_flags and i < cfg.max_iter:  # nothing is left to move: the step that finds this changes nothing
        i, change = i + 1, 0.0
        log.append((i, 0.0, 0))
    marks = frontier.merge(ever).distinct().withColumn("ever", F.lit(True))
    ranks = state if local is None else local.merged()
    out = written(ranks.select("v", "rank").join(marks, "v", "left").select("v", "rank", F.coalesce("ever", F.lit(False)).alias("ever")))
    discard(state, *ever)
    if local is not None:
        local.drop()
    return RankResult(out, i, change, visits, log, followed)


def reach_rank(g: Graph, delta: DataFrame, prev: DataFrame, cfg: RankConfig = RankConfig()) -> RankResult:
    """Only vertices reachable from the changes, from the previous ranks."""
    if resident.fits(g):
        return resident.run(g, carry_over(g, prev), resident.frontier(cfg, cfg.bar(g.n), False, False, reach=True), frontier.seed_flags(g.edges, delta))
    active, _ = frontier.reachable(g.out_edges(), frontier.seed_flags(g.out_edges(), delta), cfg.frontier_rows)
    return _frontier_loop(g, carry_over(g, prev), written(active), cfg, grow=False)


def frontier_rank(g: Graph, delta: DataFrame, prev: DataFrame, cfg: RankConfig = RankConfig(), prune: bool = False) -> RankResult:
    """An expanding frontier; with ``prune`` settled vertices leave it and the closed form is used."""
    if resident.fits(g):
        return resident.run(g, carry_over(g, prev), resident.frontier(cfg, cfg.bar(g.n), prune, True), frontier.seed_flags(g.edges, delta))
    return _frontier_loop(g, carry_over(g, prev), written(frontier.seed_flags(g.out_edges(), delta)), cfg, prune)


def run(approach: str, g: Graph, delta: DataFrame, prev: DataFrame, cfg: RankConfig = RankConfig()) -> RankResult:
    if approach == "static":
        return static_rank(g, cfg)
    if approach == "warm":
        return warm_rank(g, prev, cfg)
    if approach == "reach":
        return reach_rank(g, delta, prev, cfg)
    return frontier_rank(g, delta, prev, cfg, prune=approach == "grow_prune")


def timed(approach: str, g: Graph, delta: DataFrame, prev: DataFrame, cfg: RankConfig = RankConfig()) -> tuple[RankResult, float]:
    """A run and its seconds: seeds, marking, steps and tests of the end, on written inputs; what all approaches share is dealt out before."""
    if not resident.fits(g):
        dealt = deal(g)
        dealt.in_edges()
        sending_edges(dealt, cfg)
    began = time.perf_counter()
    result = run(approach, g, delta, prev, cfg)
    return result, time.perf_counter() - began


def replay(g: Graph, prev: DataFrame, batches: list[DataFrame], approach: str, cfg: RankConfig = RankConfig()) -> list[RankResult]:
    """Consecutive batches: the ranks of one feed the next."""
    out = []
    for delta in batches:
        edges = written(apply_delta(g.edges, delta))
        deg = written(changed_degrees(g.degrees, g.edges, delta))
        g = Graph(edges, deg, deg.count(), g.version + 1)
        result = run(approach, g, delta, prev, cfg)
        out.append(result)
        prev = result.ranks
    return out
