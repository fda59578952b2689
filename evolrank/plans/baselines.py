"""Other ways to the same ranks (or near them), kept as comparators."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from ..config import RankConfig
from ..functions.rank_math import plain_update
from ..operators import frontier
from ..operators.graph import Graph, degrees
from ..storage import bucketed, discard, fixed_partitioning, settle
from . import resident
from .engine import RankResult, _measure, carry_over, deal, pull_step, uniform


def _loop(g: Graph, cfg: RankConfig, step, start: DataFrame | None = None) -> RankResult:
    """Iterate ``step(g, ranks, i) -> (v, rank, prev, visits)`` until the norm is small."""
    g = deal(g)
    ranks, visits, delta, i, log = bucketed(start if start is not None else uniform(g), "v", g.parts), 0, float("inf"), 0, []
    while i < cfg.max_iter and delta > cfg.bar(g.n):
        made = bucketed(step(g, ranks, i), "v", g.parts)
        discard(ranks)
        i += 1
        delta, seen = _measure(made, cfg)
        visits += seen
        log.append((i, delta, seen))
        ranks = made
    return RankResult(ranks.select("v", "rank", F.lit(True).alias("ever")), i, delta, visits, log)


def _close(g: Graph, ranks: DataFrame, sums: DataFrame, cfg: RankConfig) -> DataFrame:
    state = ranks.select("v", F.col("rank").alias("prev")).join(sums, "v", "left").join(g.degrees.select("v", F.col("in_deg").alias("visits")), "v")
    return state.select("v", plain_update(F.col("total"), cfg, g.n).alias("rank"), "prev", "visits")


def push_rank(g: Graph, cfg: RankConfig = RankConfig()) -> RankResult:
    """Each source sends one row per edge to its target; rows are summed only after the shuffle."""
    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        out = ranks.join(g.degrees, "v").select(F.col("v").alias("src"), (F.col("rank") / F.col("out_deg")).alias("share"))
        sent = g.edges.join(out, "src").select("dst", "share").repartition("dst")
        return _close(g, ranks, sent.groupBy(F.col("dst").alias("v")).agg(F.sum("share").alias("total")), cfg)

    return _loop(g, cfg, step)


def two_phase_rank(g: Graph, cfg: RankConfig = RankConfig()) -> RankResult:
    """Contributions are written as a table of their own before they are pulled."""
    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        shares = settle(ranks.join(g.degrees, "v").select(F.col("v").alias("src"), (F.col("rank") / F.col("out_deg")).alias("share")))
        return _close(g, ranks, g.edges.join(shares, "src").groupBy(F.col("dst").alias("v")).agg(F.sum("share").alias("total")), cfg)

    return _loop(g, cfg, step)


def matrix_rank(g: Graph, cfg: RankConfig = RankConfig()) -> RankResult:
    """Sparse matrix times vector on prebuilt entries (row, col, weight)."""
    entries = settle(g.edges.join(g.degrees.select(F.col("v").alias("src"), "out_deg"), "src").select(F.col("dst").alias("row"), F.col("src").alias("col"), (1.0 / F.col("out_deg")).alias("weight")))

    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        product = entries.join(ranks.select(F.col("v").alias("col"), "rank"), "col").groupBy(F.col("row").alias("v")).agg(F.sum(F.col("weight") * F.col("rank")).alias("total"))
        return _close(g, ranks, product, cfg)

    return _loop(g, cfg, step)


def binned_rank(g: Graph, cfg: RankConfig = RankConfig(), bounds: tuple[int, int] = (8, 64)) -> RankResult:
    """Targets in three in-degree bins: plain, 4-way and 16-way salted sums."""
    size = F.when(F.col("in_deg") < bounds[0], 1).when(F.col("in_deg") < bounds[1], 4).otherwise(16)

    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        shares = ranks.join(g.degrees, "v").select(F.col("v").alias("src"), (F.col("rank") / F.col("out_deg")).alias("share"))
        rows = g.edges.join(shares, "src").join(g.degrees.select(F.col("v").alias("dst"), size.alias("ways")), "dst")
        part = rows.groupBy("dst", F.pmod(F.xxhash64("src"), F.col("ways")).alias("salt")).agg(F.sum("share").alias("s"))
        return _close(g, ranks, part.groupBy(F.col("dst").alias("v")).agg(F.sum("s").alias("total")), cfg)

    return _loop(g, cfg, step)


def chunked_rank(g: Graph, cfg: RankConfig = RankConfig(), chunks: int = 3) -> RankResult:
    """One chunk of targets after the other, as for graphs larger than memory."""
    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        shares = ranks.join(g.degrees, "v").select(F.col("v").alias("src"), (F.col("rank") / F.col("out_deg")).alias("share"))
        parts = [settle(g.edges.where(F.pmod(F.xxhash64("dst"), F.lit(chunks)) == c).join(shares, "src").groupBy(F.col("dst").alias("v")).agg(F.sum("share").alias("total"))) for c in range(chunks)]
        whole = parts[0]
        for p in parts[1:]:
            whole = whole.unionByName(p)
        return _close(g, ranks, whole, cfg)

    return _loop(g, cfg, step)


def switching_rank(g: Graph, cfg: RankConfig = RankConfig(), share: float = 0.05) -> RankResult:
    """Push while few vertices move, pull otherwise; the ranks do not depend on the choice."""
    moved = {"share": 1.0}

    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        out = ranks.join(g.degrees, "v").select(F.col("v").alias("src"), (F.col("rank") / F.col("out_deg")).alias("share"))
        rows = g.edges.join(out, "src").select("dst", "share")
        if moved["share"] < share:
            rows = rows.repartition("dst")
        made = settle(_close(g, ranks, rows.groupBy(F.col("dst").alias("v")).agg(F.sum("share").alias("total")), cfg))
        moved["share"] = made.agg(F.avg((F.abs(F.col("rank") - F.col("prev")) > cfg.tol).cast("double"))).first()[0]
        return made

    return _loop(g, cfg, step)


def teleport_rank(edges: DataFrame, cfg: RankConfig = RankConfig()) -> RankResult:
    """No loops: what dead ends hold is spread over all vertices in every step."""
    deg = settle(degrees(edges))
    g = Graph(edges, deg, deg.count())
    if resident.fits(g):
        return resident.run(g, uniform(g), resident.teleport(cfg, cfg.bar(g.n)))

    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        state = ranks.join(g.degrees, "v")
        lost = state.where("out_deg = 0").agg(F.coalesce(F.sum("rank"), F.lit(0.0))).first()[0]
        shares = state.where("out_deg > 0").select(F.col("v").alias("src"), (F.col("rank") / F.col("out_deg")).alias("share"))
        sums = g.edges.join(shares, "src").groupBy(F.col("dst").alias("v")).agg(F.sum("share").alias("total"))
        return _close(g, ranks, sums, cfg).withColumn("rank", F.col("rank") + cfg.alpha * lost / g.n)

    return _loop(g, cfg, step)


def personal_rank(g: Graph, sources: DataFrame, cfg: RankConfig = RankConfig()) -> RankResult:
    """Jumps lead to the vertices of ``sources`` (v) only, in equal shares; with all vertices it is the static ranking.

    Sources that the graph lacks are ignored; without any, an error is raised.
    """
    with fixed_partitioning(g.edges.sparkSession):
        home = settle(sources.select("v").distinct().join(g.degrees.select("v"), "v", "left_semi"))
    many = home.count()
    if not many:
        raise ValueError("no source is a vertex of the graph")
    share = home.select("v", F.lit(1.0 / many).alias("home"))

    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        out = ranks.join(g.degrees, "v").select(F.col("v").alias("src"), (F.col("rank") / F.col("out_deg")).alias("share"))
        sums = g.edges.join(out, "src").groupBy(F.col("dst").alias("v")).agg(F.sum("share").alias("total"))
        closed = _close(g, ranks, sums, cfg).join(share, "v", "left")
        return closed.select("v", (F.col("rank") + (1 - cfg.alpha) * (F.coalesce("home", F.lit(0.0)) - 1.0 / g.n)).alias("rank"), "prev", "visits")

    return _loop(g, cfg, step)


def strip_dead_ends(edges: DataFrame) -> DataFrame:
    """Edges left after dead ends are removed until none remains; it may be none."""
    now = settle(edges)
    left = now.count()
    while left:
        now = settle(now.join(now.select(F.col("src").alias("dst")).distinct(), "dst", "left_semi").select("src", "dst"))
        before, left = left, now.count()
        if left == before:
            break
    return now


def block_async_rank(g: Graph, cfg: RankConfig = RankConfig(), blocks: int = 3) -> RankResult:
    """Gauss-Seidel over vertex blocks: later blocks read what earlier ones wrote in the same sweep."""
    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        now = ranks
        for b in range(blocks):
            mine = g.degrees.where(F.pmod(F.xxhash64("v"), F.lit(blocks)) == b).select("v")
            now = settle(pull_step(g, now, cfg, mine).select("v", "rank"))
        return now.join(ranks.select("v", F.col("rank").alias("prev")), "v").join(g.degrees.select("v", F.col("in_deg").alias("visits")), "v").select("v", "rank", "prev", "visits")

    return _loop(g, cfg, step)


def adaptive_rank(g: Graph, cfg: RankConfig = RankConfig(), tol_freeze: float = 1e-12) -> RankResult:
    """Vertices that hardly moved in a step sit out until an in-neighbour moves."""
    held: dict = {}

    def step(g: Graph, ranks: DataFrame, i: int) -> DataFrame:
        made = settle(pull_step(g, ranks, cfg, held.get("active")))
        moving = made.where(F.abs(F.col("rank") - F.col("prev")) > tol_freeze).select("v")
        held["active"] = settle(frontier.expand(g.edges, moving))
        return made

    return _loop(g, cfg, step)


def message_rank(g: Graph, prev: DataFrame, cfg: RankConfig = RankConfig(), bar: float = 1e-13) -> RankResult:
    """Residual propagation: rank changes travel as messages (v, change) until they are small."""
    with fixed_partitioning(g.edges.sparkSession):
        g = deal(g)
        ranks = settle(carry_over(g, prev))
        first = settle(pull_step(g, ranks, cfg))
        residual, i, visits, worst = settle(first.select("v", (F.col("rank") - F.col("prev")).alias("r"))), 0, 0, float("inf")
        while i < cfg.max_iter and worst > bar:
            i += 1
            live = residual.where(F.abs(F.col("r")) > bar)
            sent = live.join(g.degrees, "v").select(F.col("v").alias("src"), (cfg.alpha * F.col("r") / F.col("out_deg")).alias("m"))
            arrived = g.edges.join(sent, "src").groupBy(F.col("dst").alias("v")).agg(F.sum("m").alias("m"))
            moved = ranks.join(live, "v", "left").select("v", (F.col("rank") + F.coalesce("r", F.lit(0.0))).alias("rank"))
            stay = residual.where(F.abs(F.col("r")) <= bar)
            residual = settle(stay.unionByName(arrived.select("v", F.col("m").alias("r"))).groupBy("v").agg(F.sum("r").alias("r")))
            ranks = settle(moved)
            worst = residual.agg(F.max(F.abs(F.col("r")))).first()[0] or 0.0
        ranks = settle(ranks.join(residual, "v", "left").select("v", (F.col("rank") + F.coalesce("r", F.lit(0.0))).alias("rank")))  # what lies under the bar
        return RankResult(ranks.withColumn("ever", F.lit(True)), i, worst, visits)


def residual_rank(g: Graph, cfg: RankConfig = RankConfig(), k: int | None = None) -> RankResult:
    """The k largest residuals (a quarter of the vertices, at least 100, if None) settle in each round until all are small.

    A batched form of a sequential method; k sets the number of rounds, not where they end.
    """
    k = k or max(100, g.n // 4)
    if resident.fits(g):
        return resident.run(g, uniform(g), resident.residual(cfg, k))
    with fixed_partitioning(g.edges.sparkSession):
        g = deal(g)
        ranks = settle(g.degrees.select("v", F.lit(0.0).alias("rank"), F.lit((1 - cfg.alpha) / g.n).alias("r")))
        i, worst = 0, 1.0
        while worst > cfg.tol_frontier / g.n:
            i += 1
            top = settle(ranks.orderBy(F.desc(F.abs("r")), "v").limit(k).select("v", "r"))
            sent = top.join(g.degrees, "v").select(F.col("v").alias("src"), (cfg.alpha * F.col("r") / F.col("out_deg")).alias("m"))
            arrived = g.edges.join(sent, "src").groupBy(F.col("dst").alias("v")).agg(F.sum("m").alias("m"))
            ranks = settle(
                ranks.join(top.select("v", F.col("r").alias("t")), "v", "left").join(arrived, "v", "left")
                .select("v", (F.col("rank") + F.coalesce("t", F.lit(0.0))).alias("rank"), (F.col("r") - F.coalesce("t", F.lit(0.0)) + F.coalesce("m", F.lit(0.0))).alias("r"))
            )
            worst = ranks.agg(F.max(F.abs("r"))).first()[0]
        return RankResult(ranks.select("v", "rank").withColumn("ever", F.lit(True)), i, worst, 0)


def walk_rank(g: Graph, walks: int = 8, cfg: RankConfig = RankConfig(), seed: int = 1) -> RankResult:
    """Monte Carlo estimate: hash-seeded walks from every vertex until the last one is absorbed, shares of visits as ranks."""
    if resident.fits(g) and g.edges.schema["src"].dataType == LongType():
        return resident.run(g, uniform(g), resident.walk(cfg, walks, seed))
    ordered = settle(g.edges.select("src", "dst", F.row_number().over(_by_src()).alias("k")))
    at = g.degrees.select(F.col("v").alias("start"), F.explode(F.sequence(F.lit(1), F.lit(walks))).alias("w")).withColumn("v", F.col("start"))
    seen, t, alive = settle(at.groupBy("v").agg(F.count("*").alias("c"))), 0, True
    while alive:
        coin = F.pmod(F.xxhash64(F.lit(seed), F.lit(t), "start", "w"), F.lit(1_000_000)) / 1e6
        at = at.where(coin < cfg.alpha).join(g.degrees.select("v", "out_deg"), "v")
        at = at.withColumn("k", F.pmod(F.xxhash64(F.lit(seed + 1), F.lit(t), "start", "w"), F.col("out_deg")) + 1)
        at = settle(at.withColumnRenamed("v", "src").join(ordered, ["src", "k"]).select("start", "w", F.col("dst").alias("v")))
        t, alive = t + 1, not at.isEmpty()
        if alive:
            seen = settle(seen.unionByName(at.groupBy("v").agg(F.count("*").alias("c"))).groupBy("v").agg(F.sum("c").alias("c")))
    total = seen.agg(F.sum("c")).first()[0]
    ranks = g.degrees.select("v").join(seen, "v", "left").select("v", (F.coalesce("c", F.lit(0)) / total).alias("rank"))
    return RankResult(ranks.withColumn("ever", F.lit(True)), t, 0.0, 0)


def _by_src():
    from pyspark.sql import Window

    return Window.partitionBy("src").orderBy("dst")


def contracted_rank(g: Graph, delta: DataFrame, prev: DataFrame, radius: int = 2, cfg: RankConfig = RankConfig()) -> RankResult:
    """Only the region around the changes is ranked again; the rest keeps its mass as a fixed boundary.

    All vertices outside act as one super-vertex whose out-flow into the region
    is what they sent before.
    """
    region = settle(frontier.seed_flags(g.edges, delta))
    for _ in range(radius - 1):
        region = settle(region.union(frontier.expand(g.edges, region)).distinct())
    start = carry_over(g, prev)
    return _loop(g, cfg, lambda g, ranks, i: pull_step(g, ranks, cfg, region), start)


def local_estimate(g: Graph, target, depth: int = 3, cfg: RankConfig = RankConfig()) -> float:
    """Rank of one vertex from the vertices that reach it within ``depth`` steps."""
    back = g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    seeds = g.degrees.where(F.col("v") == F.lit(target)).select("v")
    near = settle(seeds)
    for _ in range(depth):
        near = settle(near.union(frontier.expand(back, near)).distinct())
    ranks = settle(uniform(g))
    for _ in range(depth):
        ranks = settle(pull_step(g, ranks, cfg, near).select("v", "rank"))
    return ranks.where(F.col("v") == F.lit(target)).first().rank


def component_rank(g: Graph, delta: DataFrame, prev: DataFrame, cfg: RankConfig = RankConfig()) -> RankResult:
    """Levels of the search from the changes are ranked one after the other, then together until settled."""
    front = settle(frontier.seed_flags(g.edges, delta))
    seen, ranks = front, settle(carry_over(g, prev))
    for _ in range(3):
        ranks = settle(pull_step(g, ranks, cfg, front).select("v", "rank"))
        front = settle(frontier.expand(g.edges, front).join(seen, "v", "left_anti"))
        if front.isEmpty():
            break
        seen = settle(seen.unionByName(front))
    active, _ = frontier.reachable(g.edges, seen)
    return _loop(g, cfg, lambda g, ranks, i: pull_step(g, ranks, cfg, active), ranks)


def single_task_delta(pairs: DataFrame) -> float:
    """The largest change found by one task: the comparator of the two-level reduction."""
    return pairs.coalesce(1).select(F.max(F.abs(F.col("rank") - F.col("prev")))).first()[0]
