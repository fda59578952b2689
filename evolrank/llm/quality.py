"""Quality classifier: a sparse rule ensemble over text statistics.

Small regression trees are boosted on text statistics of a bounded, documented
sample of labelled rows; every path from a root to a node becomes a
conjunctive rule; an L1-penalised logistic fit keeps few of them; and the kept
rules are compiled into one Spark column expression, so scoring the corpus is a
plain projection without Python.

Labels come only from rows whose ``crc32(doc_id) mod 4`` is not 2.  Inputs of a
score are statistics of the text alone.

Defined results: null and empty texts have all statistics 0 and get the score
of those; a table without usable labels, or with one class only, gives the
smoothed class share as a constant score.  Repeated rows are each scored.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, text_of

SAMPLE_ROWS = 8_000  # most labelled rows that the fit reads
THRESHOLD = 0.7


def _count(text: Column, piece: str) -> Column:
    return F.length(text) - F.length(F.replace(text, F.lit(piece), F.lit("")))


def statistics(text: Column) -> dict[str, Column]:
    """Statistics of a text as JVM expressions; shares are of all characters or words."""
    n = F.length(text)
    words = F.split(F.btrim(text), r"\s+")
    n_words = F.when(n == 0, 0).otherwise(F.size(words))
    upper = n - F.length(F.regexp_replace(text, r"[\p{Lu}]+", ""))
    letters = F.length(F.regexp_replace(text, r"[^\p{L}]+", ""))
    symbols = F.length(F.regexp_replace(text, r"[^#$%&*|<>{}=_~^@\\+]+", ""))
    share = lambda x, of: F.when(of > 0, x / of).otherwise(0.0)
    return {
        "log_chars": F.log1p(n.cast("double")),
        "upper_of_letters": share(upper, letters),
        "letters_share": share(letters, n),
        "symbols_per_word": share(symbols, n_words),
        "pipes_per_word": share(_count(text, "|"), n_words),
        "shouts_per_word": share(_count(text, "!"), n_words),
        "digits_share": share(n - F.length(F.regexp_replace(text, r"[0-9]+", "")), n),
        "stops_per_word": share(_count(text, ".") + _count(text, "?"), n_words),
        "distinct_words": share(F.size(F.array_distinct(words)), n_words),
        "word_length": share(letters, n_words),
        "words_per_line": share(n_words, _count(text, "\n") + 1),
    }


FEATURES = [
    "log_chars", "upper_of_letters", "letters_share", "symbols_per_word", "pipes_per_word", "shouts_per_word",
    "digits_share", "stops_per_word", "distinct_words", "word_length", "words_per_line",
]


@dataclass(frozen=True)
class Rule:
    """A conjunction of threshold tests (feature, is_greater, threshold) and its weight."""

    tests: tuple[tuple[str, bool, float], ...]
    weight: float = 0.0

    def column(self, stats: dict[str, Column]) -> Column:
        out = None
        for name, greater, at in self.tests:
            test = stats[name] > at if greater else stats[name] <= at
            out = test if out is None else out & test
        return out

    def holds(self, x: np.ndarray, names: list[str]) -> np.ndarray:
        ok = np.ones(len(x), dtype=bool)
        for name, greater, at in self.tests:
            v = x[:, names.index(name)]
            ok &= v > at if greater else v <= at
        return ok


@dataclass
class RuleModel:
    intercept: float
    rules: list[Rule] = field(default_factory=list)

    def score(self, stats: dict[str, Column]) -> Column:
        """Probability of label 1 as one column expression."""
        total = F.lit(float(self.intercept))
        for r in self.rules:
            total = total + F.when(r.column(stats), float(r.weight)).otherwise(0.0)
        return 1.0 / (1.0 + F.exp(-total))


def _tree_paths(x: np.ndarray, g: np.ndarray, h: np.ndarray, names: list[str], depth: int, least: int) -> tuple[list[tuple], np.ndarray]:
    """Paths of one second-order regression tree, and its fitted values."""
    fit = np.zeros(len(x))
    paths: list[tuple] = []

    def grow(rows: np.ndarray, tests: tuple, left: int) -> None:
        if tests:
            paths.append(tests)
        best = None
        if left and len(rows) >= 2 * least:
            total_g, total_h = g[rows].sum(), h[rows].sum()
            base = total_g**2 / (total_h + 1.0)
            for j in range(x.shape[1]):
                order = rows[np.argsort(x[rows, j], kind="stable")]
                v = x[order, j]
                cg, ch = np.cumsum(g[order])[:-1], np.cumsum(h[order])[:-1]
                gain = cg**2 / (ch + 1.0) + (total_g - cg) ** 2 / (total_h - ch + 1.0) - base
                size = np.arange(1, len(rows))
                gain[(v[1:] <= v[:-1]) | (size < least) | (len(rows) - size < least)] = -np.inf
                k = int(np.argmax(gain))
                if gain[k] > 1e-6 and (best is None or gain[k] > best[0] + 1e-12):
                    best = (gain[k], j, float((v[k] + v[k + 1]) / 2))
        if best is None:
            fit[rows] = -g[rows].sum() / (h[rows].sum() + 1.0)
            return
        _, j, at = best
        low = x[rows, j] <= at
        grow(rows[low], (*tests, (names[j], False, at)), left - 1)
        grow(rows[~low], (*tests, (names[j], True, at)), left - 1)

    grow(np.arange(len(x)), (), depth)
    return paths, fit


def _lasso_logistic(z: np.ndarray, y: np.ndarray, penalty: float, rounds: int = 400) -> tuple[float, np.ndarray]:
    """L1-penalised logistic weights by accelerated proximal gradient steps."""
    n, p = z.shape
    step = 4.0 * n / (np.linalg.norm(np.c_[np.ones(n), z], 2) ** 2 + 1e-9)
    b, w = np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)), np.zeros(p)
    vb, vw, t = b, w.copy(), 1.0
    for _ in range(rounds):
        r = 1 / (1 + np.exp(-(vb + z @ vw))) - y
        nb = vb - step * r.mean()
        nw = vw - step * (z.T @ r) / n
        nw = np.sign(nw) * np.maximum(np.abs(nw) - step * penalty, 0.0)
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        vb, vw = nb + (t - 1) / t2 * (nb - b), nw + (t - 1) / t2 * (nw - w)
        b, w, t = nb, nw, t2
    return float(b), w


def fit_rules(x: np.ndarray, y: np.ndarray, names: list[str], trees: int = 24, depth: int = 3, penalty: float = 0.002) -> RuleModel:
    """Boost trees, take their paths as rules, and keep those with a lasso weight."""
    y = y.astype(float)
    share = (y.sum() + 1.0) / (len(y) + 2.0)
    if not len(y) or y.min() == y.max():
        return RuleModel(float(np.log(share / (1 - share))))
    least = max(3, len(y) // 400)
    f = np.full(len(y), np.log(share / (1 - share)))
    found: dict[tuple, None] = {}
    for _ in range(trees):
        p = 1 / (1 + np.exp(-f))
        paths, fit = _tree_paths(x, p - y, np.maximum(p * (1 - p), 1e-6), names, depth, least)
        found |= dict.fromkeys(tuple(sorted(set(t))) for t in paths)
        f = f + 0.3 * fit
    rules, seen = [], set()
    for tests in found:
        hold = Rule(tests).holds(x, names)
        key = hold.tobytes()
        if key not in seen and 0 < hold.sum() < len(y):
            seen.add(key)
            rules.append((tests, hold))
    z = np.array([h for _, h in rules], dtype=float).T
    b, w = _lasso_logistic(z, y, penalty)
    return RuleModel(b, [Rule(t, float(c)) for (t, _), c in zip(rules, w, strict=True) if abs(c) > 1e-3])


def training_ids(labels: DataFrame, label: str, folds: int, held_out: int, rows: int) -> DataFrame:
    """At most ``rows`` labelled training ids, spread over the table by a hash of the id.

    An id with several label rows counts once, with its largest label.
    """
    fold = F.crc32(F.col("doc_id").cast("string")) % folds
    return (
        labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & (fold != held_out))
        .groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    )


def with_statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The columns of ``docs`` in a struct ``row``, with one column for each statistic."""
    body = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), text_of(docs, text_col).alias("body"))
    return body.select("row", *[c.alias(k) for k, c in statistics(F.col("body")).items()])


def fit_quality(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> RuleModel:
    ids = training_ids(labels, "quality", 4, 2, rows)
    sample = with_statistics(docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id"))
    got = sample.select(F.col("row.doc_id").alias("doc_id"), F.col("row.y").alias("y"), *FEATURES).orderBy("doc_id", *FEATURES).limit(2 * rows).toPandas()
    return fit_rules(got[FEATURES].to_numpy(float), got["y"].to_numpy(), FEATURES)


def score_quality(docs: DataFrame, model: RuleModel, text_col: str = "text") -> DataFrame:
    """(row struct, score, predicted) for every row."""
    made = with_statistics(docs, text_col)
    # The partition number makes the score non-deterministic to the optimiser, so that no filter on
    # it is pushed below: every rule of the filter would compute all its statistics anew.
    score = F.when(F.spark_partition_id() >= 0, model.score({k: F.col(k) for k in FEATURES}))
    scored = made.select("row", score.alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit_quality(docs, table(spark, sf_dir, "labels"))
    return score_quality(docs, model).select(
        F.col("row.doc_id").alias("doc_id"), (F.crc32(F.col("row.doc_id").cast("string")) % 4 == 2).alias("held_out"), "score", "predicted"
    )
