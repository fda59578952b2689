"""Approximate nearest neighbours by largest inner product.

A hierarchical k-means tree is fitted on a bounded sample on the driver and
broadcast; its size depends on the sample only.  Every vector of the table is
routed to a leaf.  A query walks the tree best bin first: a priority queue holds
unvisited branches by how promising their centre is, and leaves come out one by
one.  How many leaves a query opens is calibrated: the true neighbours of a
fixed number of sample queries are found by brute force over all rows, and the
visit budget widens until they are recalled often enough.

Equal vectors are one entry with their smallest ids (more can never be among
the answers), so a vector that fills a third of the table costs one entry.
Large leaves are cut into blocks and many queries into groups, so no task holds
a whole leaf.

Vectors that are null, zero, of another length than the sample's usual one, or hold null
or non-finite components take no part, neither as queries nor as candidates.
Rows with a null id take no part.  Ties go to the smaller id; a repeated id is
one candidate per different vector.  An empty table, or one without a usable
vector, gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import heapq
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialise, table

SAMPLE_ROWS = 20_000  # vectors that the tree is fitted on
CALIBRATION_QUERIES = 150
RECALL = 0.96  # wanted on the calibration queries
BRANCHES = 8
LEAF_SAMPLE = 48  # sample vectors of a leaf
BLOCK = 4_096  # vectors of a leaf block, and queries of a group
TOP = 20


@dataclass
class Node:
    centres: np.ndarray  # one row for each child
    children: list  # Node, or the number of a leaf


class KMeansTree:
    """Hierarchical k-means over a sample."""

    def __init__(self, sample: np.ndarray, branches: int = BRANCHES, leaf: int = LEAF_SAMPLE, seed: int = 7):
        self.leaves = 0
        self.dim = sample.shape[1] if sample.ndim == 2 else 0
        self.rng = np.random.default_rng(seed)
        self.root = self._grow(sample, branches, leaf)

    def _grow(self, x: np.ndarray, branches: int, leaf: int):
        if len(x) <= leaf or len(np.unique(x, axis=0)) <= 1:
            self.leaves += 1
            return self.leaves - 1
        k = min(branches, max(2, -(-len(x) // leaf)))
        centres = x[self.rng.choice(len(x), k, replace=False)]
        for _ in range(12):
            near = self._near(x, centres)
            new = np.array([x[near == j].mean(axis=0) if (near == j).any() else centres[j] for j in range(k)])
            if np.allclose(new, centres):
                break
            centres = new
        near = self._near(x, centres)
        used = [j for j in range(k) if (near == j).any()]
        if len(used) == 1:
            self.leaves += 1
            return self.leaves - 1
        return Node(centres[used], [self._grow(x[near == j], branches, leaf) for j in used])

    @staticmethod
    def _near(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
        return np.argmax(x @ centres.T - 0.5 * (centres**2).sum(axis=1), axis=1)

    def route(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each row."""
        out = np.zeros(len(x), dtype=np.int32)
        stack = [(self.root, np.arange(len(x)))]
        while stack:
            node, rows = stack.pop()
            if not isinstance(node, Node):
                out[rows] = node
                continue
            near = self._near(x[rows], node.centres)
            stack += [(child, rows[near == j]) for j, child in enumerate(node.children) if (near == j).any()]
        return out

    def visits(self, q: np.ndarray, most: int) -> list[int]:
        """The first ``most`` leaves in best-bin-first order."""
        out: list[int] = []
        queue, serial = [(0.0, 0, self.root)], 1
        while queue and len(out) < most:
            _, _, node = heapq.heappop(queue)
            while isinstance(node, Node):
                worth = node.centres @ q
                best = int(np.argmax(worth))
                for j, child in enumerate(node.children):
                    if j != best:
                        heapq.heappush(queue, (-float(worth[j]), serial, child))
                        serial += 1
                node = node.children[best]
            out.append(node)
        return out


def exact_scores(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Inner products in double precision, each summed in the same order."""
    return (x.astype(np.float64) * q.astype(np.float64)).sum(axis=1)


def _top_rows(queries: np.ndarray, vectors: np.ndarray, first_ids: np.ndarray, top: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each query the places and exact scores of its best rows, ties to the smaller id."""
    out = []
    # Rounding of a product is bounded by its length and the lengths of both vectors.
    slack = 4 * vectors.shape[1] * np.finfo(float).eps * np.sqrt((vectors**2).sum(axis=1).max()) * np.sqrt((queries**2).sum(axis=1))
    for a in range(0, len(queries), 256):
        rough = vectors @ queries[a : a + 256].T
        m = min(len(vectors), top + 12)
        for j in range(rough.shape[1]):
            pick = np.argpartition(-rough[:, j], m - 1)[:m] if m < len(vectors) else np.arange(len(vectors))
            if m < len(vectors):  # everything that rounding could tie with the last place
                pick = np.flatnonzero(rough[:, j] >= rough[pick, j].min() - slack[a + j])
            s = exact_scores(vectors[pick], queries[a + j])
            order = np.lexsort((first_ids[pick], -s))[:top]
            out.append((pick[order], s[order]))
    return out


def usable_vectors(rows: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(id, v array<double>) of the rows that take part."""
    v = F.col("v")
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return (
        rows.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("v"))
        .where(F.col("id").isNotNull() & v.isNotNull()).where(~bad & F.exists(v, lambda x: x != 0))
    )


def distinct_vectors(vectors: DataFrame, ids: int) -> DataFrame:
    """(v, first, ids): each different vector with its smallest ids."""
    ranked = vectors.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("id"))).where(F.col("r") <= ids)
    return ranked.groupBy("v").agg(F.min("id").alias("first"), F.array_sort(F.collect_set("id")).alias("ids"))


def fit_tree(entries: DataFrame, rows: int = SAMPLE_ROWS) -> tuple[KMeansTree, np.ndarray] | None:
    """The tree and its sample, spread over the table by a hash of the id; none without entries."""
    got = entries.select("first", "v").orderBy(F.xxhash64("first"), "first").limit(rows).toPandas()
    if not len(got):
        return None
    dim = Counter(map(len, got["v"])).most_common(1)[0][0]
    sample = np.array([v for v in got["v"] if len(v) == dim], dtype=np.float64).reshape(-1, dim)
    return KMeansTree(sample), sample


def _matrix(v: pd.Series) -> np.ndarray:
    return np.array(v.tolist(), dtype=np.float64)


def calibrate(entries: DataFrame, tree: KMeansTree, sample: np.ndarray, recall: float = RECALL, top: int = TOP) -> int:
    """Leaf visits that recall the true neighbours of the calibration queries often enough."""
    queries = sample[:CALIBRATION_QUERIES]
    held = entries.sparkSession.sparkContext.broadcast(queries)

    def best(batches):
        for b in batches:
            x = _matrix(b["v"])
            found = _top_rows(held.value, x, b["first"].to_numpy(), top + 1)
            leaf = b["leaf"].to_numpy()
            yield pd.DataFrame({
                "q": np.repeat(np.arange(len(found)), [len(p) for p, _ in found]).astype(np.int32),
                "s": np.concatenate([s for _, s in found]), "leaf": np.concatenate([leaf[p] for p, _ in found]),
                "first": np.concatenate([b["first"].to_numpy()[p] for p, _ in found]),
            })

    ranked = entries.mapInPandas(best, "q int, s double, leaf int, first long")
    ranked = ranked.withColumn("r", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("s"), "first"))).where(F.col("r") <= top + 1)
    need = []
    for q, rows in ranked.toPandas().groupby("q"):
        place = {leaf: i + 1 for i, leaf in enumerate(tree.visits(queries[q], tree.leaves))}
        rows = rows.sort_values("r").iloc[1:]  # the first is the query itself
        need += [place[x] for x in rows["leaf"]]
    if not need:
        return max(1, tree.leaves)
    return int(np.sort(need)[min(len(need) - 1, int(np.ceil(recall * len(need))) - 1)])


def search(rows: DataFrame, query_rows: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", top: int = TOP, recall: float = RECALL) -> DataFrame:
    """(query_id, rank, vec_id, score): the nearest found of every query row, its own id excepted."""
    spark = rows.sparkSession
    entries0 = distinct_vectors(usable_vectors(rows, id_col, vector_col), top + 1)
    plain = materialise(entries0)
    fitted = fit_tree(plain)
    if fitted is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    tree, sample = fitted
    dim, leaves = tree.dim, tree.leaves
    held = spark.sparkContext.broadcast(tree)

    @F.pandas_udf("int")
    def leaf_of(v: pd.Series) -> pd.Series:
        return pd.Series(held.value.route(_matrix(v)))

    entries = materialise(plain.where(F.size("v") == dim).withColumn("leaf", leaf_of("v")))
    budget = calibrate(entries, tree, sample, recall, top)

    @F.pandas_udf("array<int>")
    def visits_of(v: pd.Series) -> pd.Series:
        return pd.Series([held.value.visits(q, budget) for q in _matrix(v)])

    own = usable_vectors(query_rows, id_col, vector_col).where(F.size("v") == dim)
    asked = materialise(own.groupBy("v").agg(F.min("id").alias("q")).withColumn("leaves", visits_of("v")))
    opened = asked.select("q", "v", F.explode("leaves").alias("leaf"))
    # Leaf counts: at most as many rows as the tree has leaves, whatever the table.
    parts = F.broadcast(
        entries.groupBy("leaf").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"))
        .join(opened.groupBy("leaf").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("groups")), "leaf")
    )
    left = entries.join(parts, "leaf").withColumn("block", F.pmod(F.xxhash64("first"), F.col("blocks"))).withColumn("group", F.explode(F.sequence(F.lit(0), F.col("groups") - 1)))
    right = opened.join(parts, "leaf").withColumn("group", F.pmod(F.xxhash64("q"), F.col("groups"))).withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    keys = ("leaf", "block", "group")
    left = left.select("leaf", F.col("block").cast("long"), F.col("group").cast("long"), "first", "v", "ids")
    right = right.select("leaf", F.col("block").cast("long"), F.col("group").cast("long"), "q", "v")

    def pairs(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        if not len(x) or not len(y):
            return pd.DataFrame({"q": [], "first": [], "ids": [], "s": []})
        found = _top_rows(_matrix(y["v"]), _matrix(x["v"]), x["first"].to_numpy(), top + 1)
        at = np.concatenate([p for p, _ in found])
        return pd.DataFrame({
            "q": np.repeat(y["q"].to_numpy(), [len(p) for p, _ in found]), "first": x["first"].to_numpy()[at],
            "ids": x["ids"].to_numpy()[at], "s": np.concatenate([s for _, s in found]),
        })

    scored = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInPandas(pairs, "q long, first long, ids array<long>, s double")
    best = scored.withColumn("r", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("s"), "first"))).where(F.col("r") <= top + 1)
    spread = best.select("q", "s", F.explode("ids").alias("id")).withColumn("r", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("s"), "id"))).where(F.col("r") <= top + 1)
    lists = spread.groupBy("q").agg(F.array_sort(F.collect_list(F.struct("r", "id", "s"))).alias("near"))
    answers = own.join(asked.select("v", "q"), "v").join(lists, "q").select(F.col("id").alias("query_id"), F.slice(F.filter("near", lambda n: n["id"] != F.col("id")), 1, top).alias("near"))
    return answers.select("query_id", F.posexplode("near").alias("p", "n")).select("query_id", (F.col("p") + 1).cast("int").alias("rank"), F.col("n.id").alias("vec_id"), F.col("n.s").alias("score"))


def op9_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return search(rows, rows.where(F.col("vec_id") % 20 == 0))
