"""The join on shingles where many copies of a text lie on either side of the bar."""

import random

import pytest
from test_operators import brute_groups

from evolrank.llm import ngram_join

VOCAB = ["v%d" % i for i in range(4000)]


def copy_of(rnd, words, changes):
    t = list(words)
    for _ in range(changes):
        t[rnd.randrange(len(t))] = rnd.choice(VOCAB)
    return " ".join(t)


def compared(spark, monkeypatch, rows):
    """Groups by id, and the number of pairs that each look at whole sets was given."""
    looked, real = [], ngram_join.verified

    def counted(pairs, *rest):
        looked.append(pairs.count())
        return real(pairs, *rest)

    monkeypatch.setattr(ngram_join, "verified", counted)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    return {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.similar_components(docs).collect()}, looked


def test_copies_under_the_bar_are_not_paired_with_each_other(spark, monkeypatch):
    rnd = random.Random(11)
    rows = []
    for _ in range(6):  # their sources are not there; 26 copies keep the tokens off the list of frequent ones
        lost = [rnd.choice(VOCAB) for _ in range(300)]
        rows += [(len(rows) + i, copy_of(rnd, lost, 14)) for i in range(26)]
    kept = [rnd.choice(VOCAB) for _ in range(300)]
    rows += [(1000, " ".join(kept))] + [(1001 + i, copy_of(rnd, kept, 4)) for i in range(12)] + [(1100 + i, copy_of(rnd, kept, 14)) for i in range(14)]
    got, looked = compared(spark, monkeypatch, rows)
    assert got == brute_groups(rows)
    assert looked[-1] <= len(rows)  # the six groups alone have 6 * 26 * 25 / 2 pairs that share enough of their prefixes


@pytest.mark.parametrize("seed", [1, 2])
def test_groups_at_all_degrees_of_change(spark, monkeypatch, seed):
    rnd, rows = random.Random(seed), []
    for _ in range(6):
        words = [rnd.choice(VOCAB) for _ in range(rnd.choice([8, 40, 150, 400]))]
        text = words + rnd.choice([[], words[: len(words) // 6]])
        for _ in range(30):
            t = copy_of(rnd, text, rnd.randrange(1 + len(text) // 16)).split(" ")
            a = rnd.randrange(1 + len(t) // 10)
            rows.append((len(rows) * 7 % 1000, " ".join(rnd.choice([t, t[a:], t[: len(t) - a], t + rnd.choices(VOCAB, k=a)]))))
    got, _ = compared(spark, monkeypatch, rows)
    assert got == brute_groups(rows)
    assert len({c for _, c in got.values()}) < len(rows)
