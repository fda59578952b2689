"""The ranking engine against brute force and its own invariants."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evolrank.config import RankConfig
from evolrank.functions import rank_math
from evolrank.operators import frontier
from evolrank.operators import graph as G
from evolrank.plans import baselines, engine, queries
from evolrank.storage import settle

EDGES = [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 5), (5, 3), (6, 7), (7, 6), (0, 6)]


def brute(edges, n, cfg=RankConfig(), start=None):
    out = np.bincount([a for a, _ in edges], minlength=n)
    r = np.full(n, 1 / n) if start is None else start
    for i in range(1, cfg.max_iter + 1):
        new = np.full(n, (1 - cfg.alpha) / n)
        for a, b in edges:
            new[b] += cfg.alpha * r[a] / out[a]
        d, r = np.abs(new - r).max(), new
        if d <= cfg.tol:
            break
    return r, i


@pytest.fixture(scope="module")
def toy(spark):
    return G.build(settle(spark.createDataFrame(EDGES, "src long, dst long")))


def vector(result, n=8):
    out = np.zeros(n)
    for row in result.ranks.collect():
        out[row.v] = row["rank"]
    return out


LOOPED = EDGES + [(v, v) for v in range(8)]


def test_static_equals_power_iteration(toy):
    cfg = RankConfig(tol=1e-3)
    want, i = brute(LOOPED, 8, cfg)
    got = engine.static_rank(toy, cfg)
    assert got.iterations == i
    assert np.allclose(vector(got), want, atol=1e-12)
    assert abs(vector(got).sum() - 1) < 1e-12
    assert vector(got).min() >= 0.15 / 8


def brute_frontier(edges, n, flags, start, cfg, prune, grow=True):
    """Ranks, ever-flagged vertices, the flags before each step, and the in-edges of all flagged vertices."""
    out = np.bincount([a for a, _ in edges], minlength=n)
    r, ever, seen, visits = start.copy(), set(flags), [set(flags)], 0
    for _ in range(cfg.max_iter):
        new = r.copy()
        for v in flags:
            total = sum(r[a] / out[a] for a, b in edges if b == v)
            visits += sum(b == v for _, b in edges)
            new[v] = 0.15 / n + 0.85 * total
            if prune:
                new[v] = (0.85 * (total - r[v] / out[v]) + 0.15 / n) / (1 - 0.85 / out[v])
        change, rel = np.abs(new - r).max(), np.abs(new - r) / np.maximum(new, r)
        if grow:
            kept = {v for v in flags if rel[v] > cfg.tol_prune} if prune else set(flags)
            flags = kept | {b for a, b in edges if a in flags and rel[a] > cfg.tol_frontier}
        r, ever = new, ever | flags
        seen.append(set(flags))
        if change <= cfg.tol:
            break
    return r, ever, seen, visits


@pytest.fixture(scope="module")
def updated(spark, toy):
    prev = engine.static_rank(toy, RankConfig(max_iter=6)).ranks
    delta = spark.createDataFrame([("ins", 5, 3), ("del", 3, 4)], "op string, src long, dst long")
    return settle(prev), settle(delta), queries.after(toy, delta)


# The first bound works on few vertices apart, the second in full steps.
@pytest.mark.parametrize("rows", [100_000, 0])
@pytest.mark.parametrize("approach", ["reach", "grow", "grow_prune"])
def test_frontiers_take_the_steps_of_brute_force(monkeypatch, updated, approach, rows):
    prev, delta, new = updated
    monkeypatch.setattr(engine, "SMALL_SHARE", 1)
    cfg = RankConfig(max_iter=4, frontier_rows=rows, tol_frontier=0.02, tol_prune=0.01, layout="none" if rows else "both", split_degree=3)
    edges = [(r.src, r.dst) for r in new.edges.collect()]
    flags = {4} | {b for a, b in edges if a in (5, 3)}
    assert {r.v for r in frontier.seed_flags(new.edges, delta).collect()} == flags
    if approach == "reach":
        flags = {r.v for r in frontier.reachable(new.edges, frontier.seed_flags(new.edges, delta), rows)[0].collect()}
    start = np.zeros(8)
    for r in prev.collect():
        start[r.v] = r["rank"]
    want, ever, _, visits = brute_frontier(edges, 8, flags, start, cfg, approach == "grow_prune", approach != "reach")
    got = engine.run(approach, new, delta, prev, cfg)
    assert np.allclose(vector(got), want, atol=1e-13)
    assert {r.v for r in got.ranks.where("ever").collect()} == ever
    assert got.edge_visits == visits


def test_no_step_shuffles_edges(updated):
    prev, _, new = updated
    g = engine.deal(new)
    flags = settle(g.degrees.where("v < 3").select("v"))
    for few in (True, False):
        plan = engine.pull_step(g, g.degrees.select("v", F.lit(0.125).alias("rank"), "out_deg", "in_deg"), RankConfig(), flags, few=few)._jdf.queryExecution().executedPlan().toString()
        dealt = [line for line in plan.split("\n") if "Exchange hashpartitioning" in line]
        assert all("hashpartitioning(src" not in line for line in dealt)
        assert sum("hashpartitioning(dst" in line for line in dealt) == 1  # the partial sums


def test_degrees_follow_a_batch(spark, toy):
    delta = spark.createDataFrame([("ins", 5, 9), ("del", 2, 3), ("ins", 0, 1), ("del", 7, 0)], "op string, src long, dst long")
    want = G.degrees(G.apply_delta(toy.edges, delta))
    assert sorted(map(tuple, G.changed_degrees(toy.degrees, toy.edges, delta).collect())) == sorted(map(tuple, want.collect()))
    wide = spark.range(3000).selectExpr("0L AS src", "id AS dst")
    chunks = G.packed_adjacency(wide, 1000).collect()
    assert len(chunks) == 3 and sorted(x for r in chunks for x in r.nbrs) == list(range(3000))


def test_empty_batch_keeps_ranks(spark, toy):
    prev = engine.uniform(toy)
    none = spark.createDataFrame([], "op string, src long, dst long")
    got = engine.run("grow_prune", toy, none, prev)
    assert got.iterations == 1 and got.edge_visits == 0


@pytest.mark.parametrize("layout", ["in", "both"])
def test_layouts_agree(toy, layout):
    got = engine.static_rank(toy, RankConfig(layout=layout, split_degree=2, salts=2, max_iter=5))
    assert np.allclose(vector(got), brute(LOOPED, 8, RankConfig(max_iter=5))[0], atol=1e-13)


@pytest.mark.parametrize("f", [baselines.push_rank, baselines.matrix_rank, baselines.chunked_rank, baselines.adaptive_rank])
def test_baselines_take_the_same_steps(toy, f):
    cfg = RankConfig(max_iter=4)
    assert np.allclose(vector(f(toy, cfg)), brute(LOOPED, 8, cfg)[0], atol=1e-10)


def test_graph_operators(spark, toy):
    delta = spark.createDataFrame([("ins", 1, 5), ("ins", 0, 1), ("del", 3, 4), ("del", 7, 0), ("ins", 2, 2)], "op string, src long, dst long")
    normal = G.normalise_delta(toy.edges, delta)
    assert {tuple(r) for r in normal.collect()} == {("ins", 1, 5), ("del", 3, 4)}
    assert {tuple(r) for r in G.diff(toy.edges, G.apply_delta(toy.edges, normal)).collect()} == {("ins", 1, 5), ("del", 3, 4)}
    seeds = spark.createDataFrame([(3,)], "v long")
    assert {r.v for r in frontier.reachable(toy.edges, seeds)[0].collect()} == {3, 4, 5}
    split = G.degree_split(toy.degrees, "in_deg", 3, 2).orderBy("pos").collect()
    assert [r.pos for r in split] == list(range(8))
    assert [r.klass for r in split] == sorted((r.klass for r in split), reverse=True)


def test_queries_run_until_settled(spark, toy, monkeypatch):
    monkeypatch.setattr(queries, "loaded", lambda *a: toy)
    monkeypatch.setattr(queries, "changed", lambda *a: (toy, None, None, toy))
    given = []

    def record(*args, **named):
        given.extend([*args, *named.items()])
        return engine.RankResult(engine.uniform(toy).withColumn("ever", F.lit(True)), 0, 0.0, 0)

    walk = baselines.walk_rank
    for f in ("block_async_rank", "adaptive_rank", "message_rank", "contracted_rank", "component_rank", "residual_rank", "walk_rank"):
        monkeypatch.setattr(baselines, f, record)
    for name in ("block_async", "adaptive", "delta_messages", "contracted", "by_components", "residual_topk", "walks"):
        queries.QUERIES[f"rank_{name}"](spark, "")
    assert not {x[0] for x in given if isinstance(x, tuple)} & {"rounds", "steps"}
    assert all(x == RankConfig() for x in [*given, *(x[1] for x in given if isinstance(x, tuple))] if isinstance(x, RankConfig))
    assert walk(toy, walks=1, cfg=RankConfig(alpha=0.2)).ranks.agg(F.round(F.sum("rank"), 9)).first()[0] == 1


def test_personal_ranks(spark, toy):
    sources, cfg = spark.createDataFrame([(3,), (3,), (99,)], "v long"), RankConfig(max_iter=6)
    edges = EDGES + [(v, v) for v in range(8)]
    out = np.bincount([a for a, _ in edges], minlength=8)
    for home, given in ((np.eye(8)[3], sources), (np.full(8, 1 / 8), toy.degrees.select("v"))):
        want = np.full(8, 1 / 8)
        for _ in range(cfg.max_iter):
            want = 0.15 * home + 0.85 * np.array([sum(want[a] / out[a] for a, b in edges if b == v) for v in range(8)])
        assert np.abs(vector(baselines.personal_rank(toy, given, cfg)) - want).max() < 1e-12
    with pytest.raises(ValueError):
        baselines.personal_rank(toy, sources.where("v = 99"))


def test_stripping_reaches_the_end_of_a_long_tail(spark):
    tail = [(v, v + 1) for v in range(10, 18)]
    left = baselines.strip_dead_ends(spark.createDataFrame([*EDGES, (0, 10), *tail], "src long, dst long"))
    assert {tuple(r) for r in left.select("src", "dst").collect()} == set(EDGES)
    assert baselines.strip_dead_ends(spark.createDataFrame(tail, "src long, dst long")).count() == 0


def test_percentiles_of_asked_vertices(spark):
    ranks = spark.createDataFrame([(v, float(v // 2)) for v in range(10)], "v long, rank double")
    assert {tuple(r) for r in rank_math.rank_percentile(ranks, [0, 1, 7, 42]).collect()} == {(0, 0.0), (1, 0.0), (7, 0.6)}
    assert rank_math.rank_percentile(ranks, [42]).count() == 0
    with pytest.raises(ValueError):
        rank_math.rank_percentile(ranks, list(range(2000)))
