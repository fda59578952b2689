"""What the third round found, each as a small case."""

import numpy as np
import pytest
from test_engine import toy, updated  # noqa: F401

from evolrank.config import RankConfig
from evolrank.operators import frontier
from evolrank.operators import graph as G
from evolrank.plans import engine, queries, resident
from evolrank.storage import settle


def brute_marking(edges, n, flags, start, cfg, approach):
    """Out-edges that marking follows, seeds left out: of every reached vertex, or of those that moved enough in a step."""
    out = np.bincount([a for a, _ in edges], minlength=n)
    if approach == "reach":
        while new := {b for a, b in edges if a in flags} - flags:
            flags = flags | new
        return sum(out[v] for v in flags)
    r, followed = start.copy(), 0
    for _ in range(cfg.max_iter):
        new = r.copy()
        for v in flags:
            total = sum(r[a] / out[a] for a, b in edges if b == v)
            new[v] = 0.15 / n + 0.85 * total
            if approach == "grow_prune":
                new[v] = (0.85 * (total - r[v] / out[v]) + 0.15 / n) / (1 - 0.85 / out[v])
        rel, r = np.abs(new - r) / np.maximum(new, r), new
        moved = {v for v in flags if rel[v] > cfg.tol_frontier}
        followed += sum(out[v] for v in moved)
        kept = {v for v in flags if rel[v] > cfg.tol_prune} if approach == "grow_prune" else flags
        flags = kept | {b for a, b in edges if a in moved}
    return followed


@pytest.mark.parametrize("most, rows", [(1000, 0), (-1, 0), (-1, 100_000)])
@pytest.mark.parametrize("approach", ["static", "reach", "grow", "grow_prune"])
def test_edges_followed_by_marking_are_counted(monkeypatch, updated, approach, most, rows):  # noqa: F811
    """In one task, in full steps and on few vertices apart."""
    prev, delta, new = updated
    monkeypatch.setattr(resident, "MOST_EDGES", most)
    monkeypatch.setattr(engine, "SMALL_SHARE", 1)
    cfg = RankConfig(max_iter=3, frontier_rows=rows, tol_frontier=0.02, tol_prune=0.01)
    edges = [(r.src, r.dst) for r in new.edges.collect()]
    start = np.zeros(8)
    for r in prev.collect():
        start[r.v] = r["rank"]
    flags = {4} | {b for a, b in edges if a in (5, 3)}
    want = 0 if approach == "static" else brute_marking(edges, 8, flags, start, cfg, approach)
    assert engine.run(approach, new, delta, prev, cfg).followed == want
    assert approach == "static" or want > 0


def test_speedup_is_of_time_and_whole_work_to_every_approach(monkeypatch, updated):  # noqa: F811
    prev, delta, new = updated
    monkeypatch.setattr(queries, "changed", lambda *a: (None, prev, delta, new))
    runs, run = {}, engine.run

    def slow(approach, *rest):
        runs[approach] = run(approach, *rest)
        return runs[approach]

    ticks = iter([0.0, 8.0, 10.0, 14.0, 20.0, 22.0, 30.0, 31.0, 40.0, 56.0])
    monkeypatch.setattr(engine, "run", slow)
    monkeypatch.setattr(engine.time, "perf_counter", lambda: next(ticks))
    made = queries.QUERIES["measure_speedup"](new.edges.sparkSession, "").collect()
    seconds = dict(zip(("static", "warm", "reach", "grow", "grow_prune"), (8.0, 4.0, 2.0, 1.0, 16.0)))
    got = {(r.approach, r.base): r for r in made}
    assert len(made) == 25 and set(got) == {(a, b) for a in seconds for b in seconds}
    seeds = sum(a in (3, 5) for a, _ in ((r.src, r.dst) for r in new.edges.collect()))
    assert frontier.seed_edges(new.degrees, delta) == seeds
    work = {a: r.edge_visits + (0 if a in ("static", "warm") else seeds + r.followed) for a, r in runs.items()}
    for (a, b), r in got.items():
        assert r.seconds == seconds[a] and r.speedup == seconds[b] / seconds[a]
        assert r.visit_ratio == runs[b].edge_visits / runs[a].edge_visits and r.work_ratio == work[b] / work[a]
    assert all(runs[a].followed > 0 for a in ("reach", "grow", "grow_prune"))


def test_error_is_to_a_reference_at_rest(spark, monkeypatch):
    """A path with a cycle at its end settles so slowly that 60 steps of the reference leave it further off than the warm ranks are."""
    edges = [(k, k + 1) for k in range(79)] + [(79, 78)]
    old = G.build(settle(spark.createDataFrame(edges, "src long, dst long")))
    delta = settle(spark.createDataFrame([("ins", 0, 2)], "op string, src long, dst long"))
    new = queries.after(old, delta)
    prev = engine.static_rank(old).ranks
    monkeypatch.setattr(queries, "changed", lambda *a: (old, prev, delta, new))
    looped = [*edges, (0, 2), *((v, v) for v in range(80))]
    out = np.bincount([a for a, _ in looped])
    way = np.zeros((80, 80))
    for a, b in looped:
        way[b, a] = 0.85 / out[a]
    rest = np.linalg.solve(np.eye(80) - way, np.full(80, 0.15 / 80))
    warm = {r.v: r["rank"] for r in engine.warm_rank(new, prev).ranks.collect()}
    want = sum(abs(warm[v] - rest[v]) for v in range(80))
    short = engine.static_rank(new, RankConfig(tol=1e-100, max_iter=60)).ranks
    cut = sum(abs(warm[r.v] - r["rank"]) for r in short.collect())
    got = queries.QUERIES["rank_error_l1"](spark, "").first().error
    print(want, cut, got)
    assert got == round(want, 9) and abs(cut - want) > 1e-6
