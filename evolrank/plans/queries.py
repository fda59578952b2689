"""All queries of the ranking engine, by name, with the SQL that checks them."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import RankConfig
from ..functions import rank_math
from ..operators import frontier, layouts
from ..operators import graph as G
from ..sources import catalog
from ..storage import discard, settle, written
from . import baselines, batches, engine
from . import sql_twins as S

CFG = RankConfig()
QUERIES: dict = {}
SQL: dict = {}
FRACTION = 1e-3


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def loaded(spark: SparkSession, sf: str, graph: str) -> G.Graph:
    raw = written(catalog.GRAPHS[graph](spark, sf).select("src", "dst"))
    edges = written(G.with_self_loops(raw))
    discard(raw)
    return _counted(edges, written(G.degrees(edges)))


def after(g: G.Graph, delta: DataFrame) -> G.Graph:
    return _counted(written(G.apply_delta(g.edges, delta)), written(G.changed_degrees(g.degrees, g.edges, delta)), g.version + 1)


def _counted(edges: DataFrame, deg: DataFrame, version: int = 0) -> G.Graph:
    n, size = deg.agg(F.count("*"), F.coalesce(F.sum("out_deg"), F.lit(0))).first()
    return G.Graph(edges, deg, n, version, {"size": size})


def changed(spark: SparkSession, sf: str, graph: str = "user_relay", fraction: float = FRACTION):
    """Old graph, its ranks, a random batch, and the new graph."""
    old = loaded(spark, sf, graph)
    delta = settle(batches.random_batch(old.edges, fraction))
    return old, engine.static_rank(old).ranks, delta, after(old, delta)


def _with(graph: str, *ctes: str, recursive: bool = True) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}" + ",\n".join([S.graph_ctes(graph), *ctes]) + "\n"


DYN = (S.power_ctes("old", S.UNIFORM, CFG), S.batch_ctes(FRACTION), S.SEEDS)

# ---- graphs -------------------------------------------------------------------------------------------------

for _g in ("part_flow", "cust_supp", "user_relay", "state_flow", "site_links", "order_road", "part_supp_sym"):
    query(f"graph_{_g}", _with(_g, recursive=False) + "SELECT src, dst FROM plain")(lambda spark, sf, g=_g: G.static_edges(catalog.GRAPHS[g](spark, sf)))
    query(f"graph_stats_{_g}", _with(_g, recursive=False) + """SELECT (SELECT n FROM num) AS n_vertices, (SELECT count(*) FROM raw) AS n_temporal, (SELECT count(*) FROM plain) AS n_edges,
  round(((SELECT count(*) FROM plain) + (SELECT n FROM num)) / CAST((SELECT n FROM num) AS DOUBLE), 6) AS avg_degree""")(lambda spark, sf, g=_g: G.describe(catalog.GRAPHS[g](spark, sf)))

query("graph_word_kmer3", r"""WITH d AS (SELECT doc_id, list_filter(string_split_regex(lower(text), '[ \t\r\n]+'), lambda x: x <> '') AS w FROM documents),
p AS (SELECT w, unnest(range(1, len(w) - 2)) AS i FROM d WHERE len(w) > 3)
SELECT DISTINCT * FROM (SELECT w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS src, w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3] AS dst FROM p) WHERE src <> dst""")(
    lambda spark, sf: G.static_edges(catalog.word_kmer(spark, sf)))

_PF = _with("part_flow", recursive=False)
query("graph_edges", _PF + "SELECT src, dst FROM plain")(lambda spark, sf: G.static_edges(catalog.part_flow(spark, sf)))
query("graph_self_loops", _PF + "SELECT src, dst FROM edges")(lambda spark, sf: G.with_self_loops(catalog.part_flow(spark, sf).select("src", "dst")))
query("graph_degrees", _PF + """SELECT v, CAST(sum(o) AS BIGINT) AS out_deg, CAST(sum(i) AS BIGINT) AS in_deg FROM (SELECT src AS v, 1 AS o, 0 AS i FROM edges UNION ALL SELECT dst, 0, 1 FROM edges) GROUP BY v""")(
    lambda spark, sf: G.degrees(G.with_self_loops(catalog.part_flow(spark, sf).select("src", "dst"))))
query("graph_transpose", _PF + "SELECT dst AS src, src AS dst FROM plain")(lambda spark, sf: G.transpose(G.static_edges(catalog.part_flow(spark, sf))))
query("packed_adjacency", _PF + "SELECT src AS v, array_to_string(list_sort(list(dst)), ',') AS nbrs FROM edges GROUP BY src")(
    lambda spark, sf: G.packed_adjacency(loaded(spark, sf, "part_flow").edges).select("v", F.array_join("nbrs", ",").alias("nbrs")))
query("graph_dead_ends", _with("site_links", recursive=False) + "SELECT v FROM verts WHERE NOT EXISTS (SELECT 1 FROM raw p WHERE p.src = v)")(
    lambda spark, sf: G.dead_ends(catalog.site_links(spark, sf)))


def _batch(spark, sf, graph="part_flow", fraction=FRACTION):
    g = loaded(spark, sf, graph)
    return g, settle(batches.random_batch(g.edges, fraction))


_RB = _with("part_flow", S.batch_ctes(FRACTION), S.SEEDS, recursive=False)
query("w_random_batch", _RB + "SELECT CAST(0 AS BIGINT) AS batch, op, src, dst FROM delta")(lambda spark, sf: _batch(spark, sf)[1].select(F.lit(0).cast("long").alias("batch"), "op", "src", "dst"))
query("graph_apply_delta", _RB + "SELECT src, dst FROM new_edges")(lambda spark, sf: (lambda g, d: G.apply_delta(g.edges, d))(*_batch(spark, sf)))
query("graph_diff", _RB + "SELECT op, src, dst FROM delta")(lambda spark, sf: (lambda g, d: G.diff(g.edges, G.apply_delta(g.edges, d)))(*_batch(spark, sf)))
query("delta_normalise", _RB + "SELECT op, src, dst FROM delta")(lambda spark, sf: (lambda g, d: G.normalise_delta(g.edges, d.unionByName(g.edges.limit(5).select(F.lit("ins").alias("op"), "src", "dst"))))(*_batch(spark, sf)))
query("seed_flags", _RB + "SELECT dst AS v FROM delta WHERE op = 'del'")(lambda spark, sf: frontier.deleted_targets(_batch(spark, sf)[1]))
query("seed_pending", _RB + "SELECT DISTINCT src AS v FROM delta")(lambda spark, sf: frontier.seed_marks(_batch(spark, sf)[1]).where("pending").select("v"))
query("seed_expanded", _RB + "SELECT v FROM seeds")(lambda spark, sf: (lambda g, d: frontier.seed_flags(G.apply_delta(g.edges, d), d))(*_batch(spark, sf)))
query("expand_once", _RB + "SELECT DISTINCT e.dst AS v FROM new_edges e JOIN seeds s ON s.v = e.src")(
    lambda spark, sf: (lambda g, d: (lambda e: frontier.expand(e, frontier.seed_flags(e, d)))(settle(G.apply_delta(g.edges, d))))(*_batch(spark, sf)))
query("expand_both", _RB + "SELECT DISTINCT e.dst AS v FROM new_edges e JOIN seeds s ON s.v = e.src")(
    lambda spark, sf: (lambda g, d: (lambda n: layouts.expand_out(n, frontier.seed_flags(n.edges, d), replace(CFG, layout="both", split_degree=32), False))(after(g, d)))(*_batch(spark, sf)))
query("reachable_set", _with("site_links", S.batch_ctes(1e-2), S.SEEDS, S.REACH) + "SELECT v FROM reach")(
    lambda spark, sf: (lambda g, d: (lambda e: frontier.reachable(e, frontier.seed_flags(e, d))[0])(settle(G.apply_delta(g.edges, d))))(*_batch(spark, sf, "site_links", 1e-2)))


@query("w_temporal_batches", _with("part_flow", recursive=False) + """, t AS (SELECT src, dst, row_number() OVER (ORDER BY ts, src, dst) - 1 AS k, count(*) OVER () AS c FROM raw),
z AS (SELECT *, CAST(floor(0.9 * c) AS BIGINT) AS head, greatest(1, CAST(round_even(0.001 * c, 0) AS BIGINT)) AS b FROM t)
SELECT CAST((k - head) // b AS BIGINT) AS batch, 'ins' AS op, src, dst FROM z WHERE k >= head AND k < head + 100 * b""")
def _temporal(spark, sf):
    return batches.temporal_slices(catalog.part_flow(spark, sf), 1e-3, 100)[1]


# ---- single steps and norms -----------------------------------------------------------------------------------

_STEP = _PF + """, s AS (SELECT e.dst AS v, sum((1.0 / n) / out_deg) AS t FROM edges e JOIN deg ON deg.v = e.src, num GROUP BY e.dst),
step AS (SELECT s.v, 0.15 / n + 0.85 * t AS plain, (0.85 * (t - (1.0 / n) / out_deg) + 0.15 / n) / (1 - 0.85 / out_deg) AS looped, 1.0 / n AS prev, n FROM s JOIN deg ON deg.v = s.v, num)
"""


def _step(spark, sf, looped=False, layout="none", active=None):
    g = loaded(spark, sf, "part_flow")
    return g, engine.pull_step(g, engine.uniform(g), replace(CFG, layout=layout, split_degree=32), active(g) if active else None, looped)


query("rank_step_plain", _STEP + "SELECT v, round(plain, 9) AS rank_r FROM step")(lambda spark, sf: _step(spark, sf)[1].select("v", F.round("rank", 9).alias("rank_r")))
query("rank_step_looped", _STEP + "SELECT v, round(looped, 9) AS rank_r FROM step")(lambda spark, sf: _step(spark, sf, True)[1].select("v", F.round("rank", 9).alias("rank_r")))
query("rank_step_active", _STEP + "SELECT v, round(CASE WHEN v % 3 = 0 THEN plain ELSE prev END, 9) AS rank_r FROM step")(
    lambda spark, sf: _step(spark, sf, active=lambda g: g.degrees.where("v % 3 = 0").select("v"))[1].select("v", F.round("rank", 9).alias("rank_r")))
for _n, _e in (("linf", "max(abs(plain - prev))"), ("l1", "sum(abs(plain - prev))"), ("l2", "sqrt(sum((plain - prev) * (plain - prev)))")):
    query(f"norm_{_n}", _STEP + f"SELECT round({_e}, 12) AS norm FROM step")(lambda spark, sf, n=_n: _step(spark, sf)[1].agg(F.round(rank_math.vector_norm(None, "rank", "prev", n), 12).alias("norm")))
query("rank_normalised", _STEP + "SELECT v, round(plain / (0.15 / n), 6) AS score FROM step")(
    lambda spark, sf: (lambda g, st: st.select("v", F.round(F.col("rank") / (0.15 / g.n), 6).alias("score")))(*_step(spark, sf)))
query("rank_mass", _STEP + "SELECT round(sum(plain), 9) AS mass FROM step")(lambda spark, sf: _step(spark, sf)[1].agg(F.round(F.sum("rank"), 9).alias("mass")))
for _l in ("none", "in", "both"):
    query(f"layout_{_l}", _STEP + "SELECT v, round(plain, 9) AS rank_r FROM step")(lambda spark, sf, x=_l: _step(spark, sf, layout=x)[1].select("v", F.round("rank", 9).alias("rank_r")))
for _s, _c in (("in", "in_deg"), ("out", "out_deg")):
    query(f"degree_split_{_s}", _PF + f""", d AS (SELECT {'dst' if _s == 'in' else 'src'} AS v, count(*) AS c FROM edges GROUP BY 1)
SELECT v, CASE WHEN c < 32 THEN 'low' ELSE 'high' END AS klass, row_number() OVER (ORDER BY CASE WHEN c < 32 THEN 0 ELSE 1 END, v) - 1 AS pos FROM d""")(
        lambda spark, sf, c=_c: G.degree_split(loaded(spark, sf, "part_flow").degrees, c, 32, 8))
query("salted_hub_sum", _with("cust_supp", recursive=False) + "SELECT dst AS v, CAST(count(*) AS DOUBLE) AS total FROM plain GROUP BY dst")(
    lambda spark, sf: layouts.high_path(G.static_edges(catalog.cust_supp(spark, sf)).withColumn("share", F.lit(1.0)), 8))

# ---- rankings ---------------------------------------------------------------------------------------------------

query("rank_static", _with("part_flow", S.power_ctes("it", S.UNIFORM, CFG)) + S.last("it"))(lambda spark, sf: engine.static_rank(loaded(spark, sf, "part_flow")).report())
for _g in ("user_relay", "state_flow", "cust_supp", "site_links", "part_supp_sym"):
    query(f"w_static_{_g}", _with(_g, S.power_ctes("it", S.UNIFORM, CFG)) + S.last("it"))(lambda spark, sf, g=_g: engine.static_rank(loaded(spark, sf, g)).report())
_FEW = replace(CFG, max_iter=5)
query("w_static_order_road", _with("order_road", S.power_ctes("it", S.UNIFORM, _FEW)) + S.last("it"))(lambda spark, sf: engine.static_rank(loaded(spark, sf, "order_road"), _FEW).report())
query("w_static_order_road_full", _with("order_road", S.power_ctes("it", S.UNIFORM, CFG)) + S.last("it"))(lambda spark, sf: engine.static_rank(loaded(spark, sf, "order_road")).report())
for _n, _f in (("push", baselines.push_rank), ("two_phase", baselines.two_phase_rank), ("spmv", baselines.matrix_rank), ("three_bins", baselines.binned_rank), ("chunked", baselines.chunked_rank), ("switching", baselines.switching_rank)):
    query(f"rank_{_n}", _with("user_relay", S.power_ctes("it", S.UNIFORM, CFG)) + S.last("it"))(lambda spark, sf, f=_f: f(loaded(spark, sf, "user_relay")).report())

_NEW_POWER = lambda name, start, active="": S.power_ctes(name, start, CFG, "new_edges", "new_deg", active)
_VIA = {
    "static": (_NEW_POWER("it", S.UNIFORM),),
    "warm": (_NEW_POWER("it", S.OLD),),
    "reach": (S.REACH, _NEW_POWER("it", S.OLD, "reach")),
    "grow": (S.frontier_ctes("it", S.OLD, CFG, False),),
    "grow_prune": (S.frontier_ctes("it", S.OLD, CFG, True),),
}


def _approach(spark, sf, approach, graph="user_relay"):
    _, prev, delta, new = changed(spark, sf, graph)
    return engine.run(approach, new, delta, prev)


for _a in ("warm", "reach", "grow", "grow_prune"):
    query(f"rank_{_a}", _with("user_relay", *DYN, *_VIA[_a]) + S.last("it"))(lambda spark, sf, a=_a: _approach(spark, sf, a).report())
    query(f"rank_{_a}_part_flow", _with("part_flow", *DYN, *_VIA[_a]) + S.last("it"))(lambda spark, sf, a=_a: _approach(spark, sf, a, "part_flow").report())


def _rename(ctes: tuple, name: str) -> tuple:
    return tuple(c.replace("it(", f"{name}(").replace("FROM it ", f"FROM {name} ") if c != S.REACH else c for c in ctes)


_ALL = [c for a in ("static", "warm", "reach", "grow", "grow_prune") for c in _rename(_VIA[a], f"x_{a}")]


def _all_runs(spark, sf):
    _, prev, delta, new = changed(spark, sf)
    return new, {a: engine.run(a, new, delta, prev) for a in _VIA}


@query("edge_visits", _with("user_relay", *DYN, *_ALL) + " UNION ALL ".join(f"SELECT '{a}' AS approach, CAST(sum(visits) AS BIGINT) AS visits, CAST(max(i) AS BIGINT) AS iterations FROM x_{a}" for a in _VIA))
def _visits(spark, sf):
    _, runs = _all_runs(spark, sf)
    return spark.createDataFrame([(a, r.edge_visits, r.iterations) for a, r in runs.items()], "approach string, visits long, iterations long")


@query("affected_share", _with("user_relay", *DYN, *_ALL) + " UNION ALL ".join(
    [f"SELECT '{a}' AS approach, count(*) FILTER (WHERE ever) AS ever, count(*) AS n FROM x_{a} WHERE i = (SELECT max(i) FROM x_{a})" for a in ("grow", "grow_prune")]
    + ["SELECT 'reach' AS approach, (SELECT count(*) FROM reach) AS ever, (SELECT n FROM num) AS n"]))
def _share(spark, sf):
    new, runs = _all_runs(spark, sf)
    return spark.createDataFrame([(a, runs[a].ranks.where("ever").count(), new.n) for a in ("grow", "grow_prune", "reach")], "approach string, ever long, n long")


_REFERENCE = replace(CFG, tol=1e-100)  # with the limit of 500 iterations that every ranking has


@query("rank_error_l1", _with("user_relay", *DYN, _NEW_POWER("it", S.OLD), S.power_ctes("ref", S.UNIFORM, _REFERENCE, "new_edges", "new_deg"))
       + "SELECT round(sum(abs(a.r - b.r)), 9) AS error FROM it a JOIN ref b ON a.v = b.v WHERE a.i = (SELECT max(i) FROM it) AND b.i = (SELECT max(i) FROM ref)")
def _error(spark, sf):
    _, prev, delta, new = changed(spark, sf)
    ref = engine.static_rank(new, _REFERENCE)
    return rank_math.rank_error(engine.warm_rank(new, prev).ranks, ref.ranks).select(F.round("error", 9).alias("error"))


@query("rank_iterations", _with("user_relay", S.power_ctes("it", S.UNIFORM, CFG)) + "SELECT CAST(max(i) AS BIGINT) AS iterations FROM it")
def _iterations(spark, sf):
    return spark.createDataFrame([(engine.static_rank(loaded(spark, sf, "user_relay")).iterations,)], "iterations long")


@query("replay_three_batches")
def _replay(spark, sf):
    pre, rows = batches.temporal_slices(catalog.user_relay(spark, sf), 1e-3, 3)
    g = G.build(settle(pre))
    rows = settle(rows)
    results = engine.replay(g, engine.static_rank(g).ranks, [rows.where(F.col("batch") == b).select("op", "src", "dst") for b in range(3)], "grow_prune")
    out = None
    for b, r in enumerate(results):
        part = r.ranks.select(F.lit(b).cast("long").alias("batch"), "v", F.round("rank", 9).alias("rank_r"))
        out = part if out is None else out.unionByName(part)
    return out


@query("rank_teleport", _with("site_links", f"""pdeg AS (SELECT v, (SELECT count(*) FROM plain p WHERE p.src = v) AS out_deg FROM verts),
it(i, v, r, d) AS (SELECT 0, v, 1.0 / (SELECT n FROM num), CAST('inf' AS DOUBLE) FROM verts UNION ALL
  SELECT o.i + 1, o.v, x.nr, max(abs(x.nr - o.r)) OVER () FROM it o JOIN (
    SELECT q.v, 0.15 / (SELECT n FROM num) + 0.85 * coalesce(t.s, 0) + 0.85 * l.lost / (SELECT n FROM num) AS nr FROM it q
    LEFT JOIN (SELECT p.dst AS v, sum(s.r / g.out_deg) AS s FROM it s JOIN plain p ON p.src = s.v JOIN pdeg g ON g.v = s.v GROUP BY p.dst) t ON t.v = q.v
    CROSS JOIN (SELECT coalesce(sum(s.r), 0) AS lost FROM it s JOIN pdeg g ON g.v = s.v WHERE g.out_deg = 0) l) x ON x.v = o.v
  WHERE o.d > {CFG.tol} AND o.i < {CFG.max_iter})""") + S.last("it"))
def _teleport(spark, sf):
    links = settle(catalog.site_links(spark, sf))
    return baselines.teleport_rank(settle(G.static_edges(links))).report()


query("rank_personal", _with("user_relay", f"""home AS (SELECT v, 1.0 / count(*) OVER () AS h FROM verts WHERE v % 7 = 0),
it(i, v, r, d) AS (SELECT 0, v, CAST(1.0 / (SELECT n FROM num) AS DOUBLE), CAST('inf' AS DOUBLE) FROM verts UNION ALL
  SELECT o.i + 1, o.v, x.nr, max(abs(x.nr - o.r)) OVER () FROM it o JOIN (
    SELECT e.dst AS v, 0.15 * coalesce(max(h.h), 0) + 0.85 * sum(s.r / g.out_deg) AS nr
    FROM it s JOIN edges e ON e.src = s.v JOIN deg g ON g.v = s.v LEFT JOIN home h ON h.v = e.dst GROUP BY e.dst) x ON x.v = o.v
  WHERE o.d > {CFG.tol} AND o.i < {CFG.max_iter})""") + S.last("it"))(
    lambda spark, sf: (lambda g: baselines.personal_rank(g, g.degrees.where("v % 7 = 0").select("v"), CFG).report())(loaded(spark, sf, "user_relay")))
# Page links have no cycle and fall away step by step; the relay of users is all cycles and stays.
query("strip_two_parts", _with("site_links", f"""relay AS ({S.TEMPORAL['user_relay']}),
parts AS (SELECT src, dst FROM plain UNION SELECT CAST(src AS VARCHAR), CAST(dst AS VARCHAR) FROM relay WHERE src <> dst),
far(a, b) AS (SELECT src, dst FROM parts UNION SELECT far.a, e.dst FROM far JOIN parts e ON e.src = far.b),
ring AS (SELECT DISTINCT a AS v FROM far WHERE a = b),
alive AS (SELECT v FROM ring UNION SELECT far.a FROM far JOIN ring ON ring.v = far.b)""") + "SELECT src, dst FROM parts WHERE dst IN (SELECT v FROM alive)")(
    lambda spark, sf: baselines.strip_dead_ends(G.static_edges(catalog.site_links(spark, sf).select("src", "dst").unionByName(catalog.user_relay(spark, sf).select(F.col("src").cast("string"), F.col("dst").cast("string"))))))
query("rank_stripped")(lambda spark, sf: (lambda e: e.groupBy("src").agg(F.count("*").alias("left")))(baselines.strip_dead_ends(G.static_edges(catalog.part_flow(spark, sf)))))
query("rank_block_async")(lambda spark, sf: baselines.block_async_rank(loaded(spark, sf, "user_relay"), CFG).report())
query("rank_adaptive")(lambda spark, sf: baselines.adaptive_rank(loaded(spark, sf, "user_relay"), CFG).report())
query("rank_delta_messages")(lambda spark, sf: (lambda o, p, d, n: baselines.message_rank(n, p, CFG).report())(*changed(spark, sf)))
query("rank_residual_topk")(lambda spark, sf: baselines.residual_rank(loaded(spark, sf, "user_relay")).report())
query("rank_walks")(lambda spark, sf: baselines.walk_rank(loaded(spark, sf, "user_relay"), walks=20).report())
query("rank_contracted")(lambda spark, sf: (lambda o, p, d, n: baselines.contracted_rank(n, d, p, cfg=CFG).report())(*changed(spark, sf)))
query("rank_by_components")(lambda spark, sf: (lambda o, p, d, n: baselines.component_rank(n, d, p, CFG).report())(*changed(spark, sf)))


@query("rank_local_estimate")
def _local(spark, sf):
    g = loaded(spark, sf, "user_relay")
    return spark.createDataFrame([(1, baselines.local_estimate(g, 1))], "v long, estimate double")


@query("rank_param_sweep")
def _sweep(spark, sf):
    """Iterations, work and error of the pruning frontier for several tolerances."""
    _, prev, delta, new = changed(spark, sf)
    ref = engine.static_rank(new, replace(CFG, tol=1e-100, max_iter=60)).ranks
    rows = []
    for f in (1e-4, 1e-6, 1e-8):
        for p in (1e-4, 1e-6, 1e-8):
            r = engine.frontier_rank(new, delta, prev, replace(CFG, tol_frontier=f, tol_prune=p), True)
            rows.append((f, p, r.iterations, r.edge_visits, rank_math.rank_error(r.ranks, ref).first().error))
    return spark.createDataFrame(rows, "tol_frontier double, tol_prune double, iterations long, visits long, error double")


# ---- measures ---------------------------------------------------------------------------------------------------

_MEANS = """WITH m AS (SELECT o_orderstatus AS s, o_orderpriority AS p, avg(o_totalprice) AS a FROM orders GROUP BY 1, 2),
b AS (SELECT s, a FROM m WHERE p = '1-URGENT')
"""


@query("measure_indirect", _MEANS + """SELECT m.s || ':' || m.p AS row_id, round((m.a / b.a) * (b.a / (SELECT avg(o_totalprice) FROM orders)), 6) AS speedup FROM m JOIN b ON b.s = m.s""")
def _indirect(spark, sf):
    """Mean price of each status and priority: measured against the urgent orders of that status, these against all orders."""
    orders = catalog.table(spark, sf, "orders").select(F.col("o_orderstatus").alias("base_id"), F.col("o_orderpriority").alias("p"), "o_totalprice")
    means = settle(orders.groupBy("base_id", "p").agg(F.avg("o_totalprice").alias("a")))
    bases = means.where("p = '1-URGENT'").select("base_id", F.col("a").alias("base_mean"))
    rows = means.join(bases, "base_id").select(F.concat_ws(":", "base_id", "p").alias("row_id"), "base_id", (F.col("a") / F.col("base_mean")).alias("ratio"))
    whole = orders.agg(F.avg("o_totalprice").alias("whole"))
    return rank_math.indirect_ratio(rows, bases.crossJoin(F.broadcast(whole)).select("base_id", (F.col("base_mean") / F.col("whole")).alias("base")))


query("measure_geomean", "SELECT o_orderstatus, round(exp(avg(ln(o_totalprice))), 4) AS geomean FROM orders GROUP BY o_orderstatus")(
    lambda spark, sf: catalog.table(spark, sf, "orders").groupBy("o_orderstatus").agg(F.round(rank_math.geometric_mean(F.col("o_totalprice")), 4).alias("geomean")))
@query("recommend_approach", """WITH b AS (SELECT o_orderdate AS day, CASE WHEN o_orderstatus = 'O' THEN 'temporal' ELSE 'random' END AS kind, o_orderpriority = '1-URGENT' AS error_matters, count(*) AS c
  FROM orders GROUP BY 1, 2, 3), t AS (SELECT count(*) AS n FROM orders)
SELECT day, kind, error_matters, c AS changes, CASE WHEN error_matters OR (kind = 'random' AND CAST(c AS DOUBLE) / n > 1e-4) THEN 'warm' ELSE 'grow_prune' END AS approach FROM b, t""")
def _recommend(spark, sf):
    """Orders as batches of changes, by day: open ones arrive in order of time, the others in none; urgent ones must be exact."""
    orders = catalog.table(spark, sf, "orders").select(
        F.col("o_orderdate").alias("day"), F.when(F.col("o_orderstatus") == "O", "temporal").otherwise("random").alias("kind"), (F.col("o_orderpriority") == "1-URGENT").alias("error_matters"))
    whole = orders.agg(F.count("*").cast("double").alias("n"))
    made = orders.groupBy("day", "kind", "error_matters").agg(F.count("*").alias("changes")).crossJoin(F.broadcast(whole))
    choice = rank_math.recommend_column(F.col("kind"), F.col("changes") / F.col("n"), F.coalesce("error_matters", F.lit(False)))
    return made.select("day", "kind", "error_matters", "changes", choice.alias("approach"))


@query("measure_speedup")
def _speedup(spark, sf):
    """Time and work of each approach against the static one and each other, on one random batch.

    Work is all edges gone along: into recomputed vertices, and out of those whose neighbours were marked, seeds and search included.
    """
    _, prev, delta, new = changed(spark, sf)
    seeds, rows = frontier.seed_edges(new.degrees, delta), []
    for a in _VIA:
        r, seconds = engine.timed(a, new, delta, prev)
        marked = 0 if a in ("static", "warm") else seeds + r.followed
        rows.append((a, seconds, r.edge_visits, r.edge_visits + marked))
    return rank_math.speedups(spark.createDataFrame(rows, "approach string, seconds double, visits long, work long"))


@query("explain_vertex", _STEP + """SELECT e.src AS v, round((1.0 / n) / out_deg, 12) AS share FROM edges e JOIN deg ON deg.v = e.src, num WHERE e.dst = 7""")
def _explain(spark, sf):
    g = loaded(spark, sf, "part_flow")
    return g.edges.where("dst = 7").join(g.degrees, F.col("src") == F.col("v")).select("v", F.round(F.lit(1.0 / g.n) / F.col("out_deg"), 12).alias("share"))


_ASKED = (1, 7, 50, 100)


@query("rank_percentile", _STEP + f"SELECT a.v, round(count(*) FILTER (WHERE round(b.plain, 9) < round(a.plain, 9)) / CAST(count(*) AS DOUBLE), 9) AS below FROM step a, step b WHERE a.v IN {_ASKED} GROUP BY a.v")
def _percentile(spark, sf):
    ranks = _step(spark, sf)[1].select("v", F.round("rank", 9).alias("rank"))
    return rank_math.rank_percentile(ranks, list(_ASKED))
