"""Nulls, empty and very long texts, repeated rows, clashing names and empty tables, for each operator that reads texts or vectors."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evolrank.llm import ann, common, decontaminate, licenses, quality, secrets_scan, toxicity

SCHEMA = "doc_id long, text string, d string, row int, b string, score double"
LONG = "plain words " * 20_000
ROWS = [
    (1, None), (2, ""), (3, LONG), (4, "you idiot, token=abcdefgh1234. Released under the MIT License."),
    (4, "you idiot, token=abcdefgh1234. Released under the MIT License."), (None, "no id, you idiot. Released under the MIT License."),
    (5, "one two three four five six seven eight nine ten eleven twelve thirteen fourteen"), (6, "eyJ" * 100_000),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, "x", 1, "y", 0.5) for i, t in ROWS], SCHEMA).repartition(2).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_quality(odd, none):
    model = quality.RuleModel(0.5, [quality.Rule((("log_chars", True, 3.0), ("digits_share", False, 0.5)), 1.0)])
    scored = quality.score_quality(odd, model)
    rows = scored.select("row.doc_id", "score", "predicted").collect()
    assert len(rows) == len(ROWS)
    want = {1: 0.5, 2: 0.5, 3: 1.5, 4: 1.5, None: 1.5, 5: 1.5, 6: 1.5}
    assert all(abs(r.score - 1 / (1 + np.exp(-want[r.doc_id]))) < 1e-12 for r in rows)
    assert quality.score_quality(none, model).count() == 0
    # A filter on the prediction must not compute the statistics of the rules again.
    plan = scored.where("predicted = 1")._jdf.queryExecution().optimizedPlan().toString()
    assert not [x for x in plan.split("\n") if "Filter" in x and "regexp_replace" in x]


def test_toxicity(odd, none):
    model = toxicity.ToxicModel()
    rows = toxicity.score_toxicity(odd, model).collect()
    base = 1 / (1 + np.exp(2.5))
    assert len(rows) == len(ROWS)
    assert all(abs(r.score - base) < 1e-12 for r in rows if r.doc_id in (1, 2, 3, 5, 6))
    assert all(r.score > base for r in rows if r.doc_id in (4, None))
    assert toxicity.score_toxicity(none, model).count() == 0


def test_a_clause_is_read_whole():
    read = toxicity.Grammar([]).read
    softened = toxicity.LABELS.index("softened")
    assert read("he said " + "word " * 500 + "you are an idiot")[softened] == 1
    assert read("he said so. " + "word " * 500 + "you are an idiot")[softened] == 0


def test_secrets(odd, none):
    rows = secrets_scan.scan_digests(odd).collect()
    assert len(rows) == len(ROWS)
    assert all((r.n_assign, r.n_access, r.n_hex) == ((1, 0, 0) if r.doc_id == 4 else (0, 0, 0)) for r in rows)
    assert secrets_scan.scan_digests(none).count() == 0


def test_licenses(odd, none):
    assert [tuple(r) for r in licenses.scan_licenses(odd).select("doc_id", "license").collect()] == [(4, "MIT notice")]
    assert licenses.scan_licenses(none).count() == 0


def test_decontamination(spark, odd, none):
    items = spark.createDataFrame([(1, ROWS[6][1]), (1, ROWS[6][1]), (2, None), (3, "too short"), (None, ROWS[6][1])], "item_id long, text string")
    assert [tuple(r) for r in decontaminate.leaks(odd, items).select("doc_id", "item_id").collect()] == [(5, 1)]
    kept = decontaminate.decontaminate(odd, items)
    assert kept.columns == odd.columns and kept.count() == len(ROWS) - 1
    assert decontaminate.leaks(none, items).count() == 0
    assert decontaminate.leaks(odd, items.limit(0)).count() == 0


def test_nearest(spark):
    schema = "vec_id long, embedding array<double>, q long, v string"
    rows = [(i, [float(i), 1e6], 0, "x") for i in range(1, 6)] + [(5, [5.0, 1e6], 0, "x"), (7, None, 0, "x"), (8, [0.0, 0.0], 0, "x"), (9, [1.0, None], 0, "x"), (None, [1.0, 1.0], 0, "x")]
    table = spark.createDataFrame(rows, schema)
    found = ann.search(table, table.where("vec_id IN (1, 7, 8)"), top=3).orderBy("query_id", "rank").collect()
    assert [(r.query_id, r["rank"], r.vec_id, r.score) for r in found] == [(1, k + 1, 5 - k, 5.0 - k + 1e12) for k in range(3)]
    empty = spark.createDataFrame([], schema)
    assert ann.search(empty, empty).count() == 0
    assert ann.search(table.where("vec_id > 6"), table).count() == 0


def test_slices_bound_the_text_at_once():
    import pyarrow as pa

    batch = pa.RecordBatch.from_arrays([pa.array(range(6)), pa.array(["aa", None, "b" * 9, "", "cc", "d"])], names=["i", "t"])
    assert [x.column(0).to_pylist() for x in common.slices(batch, 1, 4)] == [[0, 1], [2], [3, 4, 5]]
