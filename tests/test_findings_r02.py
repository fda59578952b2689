"""What the second round found, each as a small case."""

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_engine import EDGES

from evolrank.config import RankConfig
from evolrank.operators import frontier
from evolrank.operators import graph as G
from evolrank.plans import baselines, engine, queries, resident
from evolrank.sources import catalog
from evolrank.storage import settle


def test_a_target_of_two_deletions_is_flagged_for_each(spark, monkeypatch):
    delta = spark.createDataFrame([("del", 1, 9), ("del", 2, 9), ("del", 3, 4), ("ins", 5, 6)], "op string, src long, dst long")
    monkeypatch.setattr(queries, "_batch", lambda *a: (None, delta))
    assert sorted(r.v for r in queries.QUERIES["seed_flags"](spark, "").collect()) == [4, 9, 9]
    assert sorted((r.v, r.flagged) for r in frontier.seed_marks(delta).collect() if r.flagged) == [(4, True), (9, True)]


@pytest.mark.parametrize("approach, norm", [("static", "l1"), ("warm", "l2"), ("reach", "linf"), ("grow", "l2"), ("grow_prune", "linf")])
def test_one_task_takes_the_steps_of_dealt_edges(spark, monkeypatch, approach, norm):
    """Also with names for vertices; and in one task no table is dealt out."""
    toy = G.build(settle(spark.createDataFrame([(f"p{a}", f"p{b}") for a, b in EDGES], "src string, dst string")))
    delta = spark.createDataFrame([("ins", "p5", "p3"), ("del", "p3", "p4"), ("ins", "new", "p0")], "op string, src string, dst string")
    cfg = RankConfig(max_iter=3, tol_frontier=0.02, tol_prune=0.01, norm=norm)
    prev, new = engine.uniform(toy), queries.after(toy, delta)
    seen = []
    for most in (-1, 10):
        monkeypatch.setattr(resident, "MOST_EDGES", most if most < 0 else new.size())
        if most > 0:
            monkeypatch.setattr(engine, "bucketed", None)
        seen.append(engine.run(approach, new, delta, prev, cfg))
    a, b = seen
    assert (a.iterations, a.edge_visits, [x[2] for x in a.log]) == (b.iterations, b.edge_visits, [x[2] for x in b.log])
    assert abs(a.delta - b.delta) < 1e-14
    rows = [{r.v: (round(r["rank"], 13), r.ever) for r in x.ranks.collect()} for x in seen]
    assert rows[0] == rows[1] and "new" in rows[0]


def _both(monkeypatch, rank):
    """The reports of a ranking with dealt-out edges and in one task; there no table is dealt out or checkpointed step by step."""
    monkeypatch.setattr(resident, "MOST_EDGES", -1)
    dealt = sorted(map(tuple, rank().report().collect()))
    monkeypatch.setattr(resident, "MOST_EDGES", 1000)
    for name in ("_measure", "bucketed", "deal"):
        monkeypatch.setattr(baselines, name, None)
    return dealt, sorted(map(tuple, rank().report().collect()))


def test_teleport_in_one_task(spark, monkeypatch):
    edges = settle(spark.createDataFrame([(f"p{a}", f"p{b}") for a, b in [*EDGES, (1, 9)]], "src string, dst string"))
    dealt, one = _both(monkeypatch, lambda: baselines.teleport_rank(edges, RankConfig(max_iter=4)))
    assert dealt == one and len(one) == 9


def test_residuals_in_one_task(spark, monkeypatch):
    toy = G.build(settle(spark.createDataFrame(EDGES, "src long, dst long")))
    dealt, one = _both(monkeypatch, lambda: baselines.residual_rank(toy, RankConfig(tol_frontier=0.08), k=3))
    assert dealt == one and one[0][2] > 2


def test_walks_in_one_task(spark, monkeypatch):
    toy = G.build(settle(spark.createDataFrame(EDGES, "src long, dst long")))
    walk = lambda: baselines.walk_rank(toy, walks=3, cfg=RankConfig(alpha=0.4))
    dealt, one = _both(monkeypatch, walk)
    assert dealt == one and one[0][2] > 1
    lots = resident.walk
    monkeypatch.setattr(resident, "walk", lambda *a: lots(*a, lot=5))
    assert sorted(map(tuple, walk().report().collect())) == one


def test_hashes_are_those_of_spark(spark):
    rows = [(a, b) for a in (0, 1, -7, 2**31 - 1, -2**31) for b in (0, 5, -1, 2**63 - 1, -2**63)]
    want = spark.createDataFrame(rows, "a int, b long").select(F.xxhash64("a", "b", "a").alias("h"))
    a, b = (np.array(x, kind) for x, kind in zip(zip(*rows), (np.int32, np.int64)))
    assert [r.h for r in want.collect()] == list(resident.spark_hash(a, b, a))


def test_the_relay_goes_over_empty_hours(spark, tmp_path):
    """Events without a time come first, and the plan has no window over all events."""
    hours = [None, None, "2024-01-01 00:10:00", "2024-01-01 00:50:00", "2024-01-01 00:50:00", "2024-01-01 07:00:00", "2024-01-03 07:30:00"]
    rows = [(k, at, user) for k, (at, user) in enumerate(zip(hours, (5, 6, 7, None, 9, 7, 8)))]
    spark.createDataFrame(rows[::-1], "event_id long, t string, user_id long").selectExpr("event_id", "CAST(t AS timestamp_ntz) AS ts", "user_id").write.parquet(str(tmp_path / "events.parquet"))
    got = catalog.user_relay(spark, str(tmp_path))
    assert sorted((str(r.src), r.dst) for r in got.collect()) == sorted((str(a[2]), b[2]) for a, b in zip(rows, rows[1:]) if b[2] is not None)
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert sum("Window [" in line and "windowspecdefinition(slice" in line for line in plan.split("\n")) == 2


def _orders(spark, folder, rows):
    spark.createDataFrame(rows, "o_orderdate string, o_orderstatus string, o_orderpriority string, o_totalprice double").write.parquet(str(folder / "orders.parquet"))
    return str(folder)


def test_indirect_measures_come_from_orders(spark, tmp_path):
    sf = _orders(spark, tmp_path, [("d", "F", "1-URGENT", 2.0), ("d", "F", "5-LOW", 6.0), ("d", "O", "1-URGENT", 4.0), ("d", "O", "2-HIGH", 1.0), ("d", "O", "2-HIGH", 3.0), ("d", "P", "5-LOW", 8.0)])
    assert sorted(map(tuple, queries.QUERIES["measure_indirect"](spark, sf).collect())) == [("F:1-URGENT", 0.5), ("F:5-LOW", 1.5), ("O:1-URGENT", 1.0), ("O:2-HIGH", 0.5)]


def test_approaches_are_chosen_for_batches_of_orders(spark, tmp_path):
    sf = _orders(spark, tmp_path, [("a", "F", "1-URGENT", 1.0), ("a", "F", "5-LOW", 1.0), ("a", "O", "5-LOW", 1.0), ("b", "P", "2-HIGH", 1.0)] + 9_996 * [("c", "O", "3-MEDIUM", 1.0)])
    got = {(r.day, r.kind, r.error_matters): (r.changes, r.approach) for r in queries.QUERIES["recommend_approach"](spark, sf).collect()}
    assert got == {("a", "random", True): (1, "warm"), ("a", "random", False): (1, "grow_prune"), ("a", "temporal", False): (1, "grow_prune"), ("b", "random", False): (1, "grow_prune"), ("c", "temporal", False): (9_996, "grow_prune")}
    (tmp_path / "more").mkdir()
    sf = _orders(spark, tmp_path / "more", [("a", "F", "5-LOW", 1.0), ("a", "O", "5-LOW", 1.0)])
    assert {(r.kind, r.approach) for r in queries.QUERIES["recommend_approach"](spark, sf).collect()} == {("random", "warm"), ("temporal", "grow_prune")}
