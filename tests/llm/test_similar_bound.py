"""The near-duplicate stage's bound by parities: it loses no link, and what it lets pass does not grow with the square of a group."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_similar import linked

import corpus_pipeline
from spanweave.llm import similar

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def compared(spark, monkeypatch, texts):
    """Ids that stay, and how many pairs were compared in full."""
    seen, alike = [], similar.alike
    monkeypatch.setattr(similar, "alike", lambda pairs, *a: seen.append(pairs.count()) or alike(pairs, *a))
    docs = spark.createDataFrame([(k, t, "en", "s", len(t)) for k, t in texts.items()], SCHEMA)
    return {d["doc_id"] for d in corpus_pipeline.one_of_each_group(spark, docs, "").collect()}, sum(seen)


def edited(r, words, at):
    """The words with the words at these places replaced by others."""
    return " ".join(f"e{r.randrange(10**9)}" if k in at else w for k, w in enumerate(words))


def test_copies_below_the_bound_are_not_compared_pair_by_pair(spark, monkeypatch):
    r = random.Random(4)
    words = [f"w{k}" for k in range(150)]
    texts = {k: edited(r, words, set(r.sample(range(150), r.choice([4, 5, 6])))) for k in range(80)}
    pairs = linked(texts)
    kept, full = compared(spark, monkeypatch, texts)
    assert len(pairs) < 40
    assert all(b not in kept for _, b, _ in pairs) and set(texts) - kept <= {b for _, b, _ in pairs}
    assert full < 400  # of 3,160 pairs


@pytest.mark.parametrize("size", [1, 4, 9, 90, 900, 9000])
def test_every_pair_that_is_alike_may_be(spark, size):
    """Pairs at the very bound, 9c = 4 (n + m), and ones beside it."""
    r, rows = np.random.default_rng(size), []
    for n, m in {(size, size), (size, max(1, size * 4 // 5)), (size, size * 9 // 10 or 1)}:
        for c in {min(n, m, -(-4 * (n + m) // 9)), min(n, m), max(0, min(n, m) - 1 - size // 3)}:
            pool = np.unique(r.integers(0, 1 << 63, n + m + 5, dtype=np.uint64) * np.uint64(2) + np.uint64(1))[: n + m - c]
            r.shuffle(pool)
            a, b = pool[:n], pool[n - c : n - c + m]
            assert len(np.intersect1d(a, b)) == c
            rows.append((n, similar.parities(a).tolist(), m, similar.parities(b).tolist(), bool(9 * c >= 4 * (n + m))))
    df = spark.createDataFrame(rows, "n int, odd array<bigint>, m int, even array<bigint>, alike boolean")
    df = df.select(F.struct("n", "odd").alias("a"), F.struct(F.col("m").alias("n"), F.col("even").alias("odd")).alias("b"), "alike")
    got = df.select("alike", similar.may_be_alike("a", "b").alias("may")).collect()
    assert any(g["alike"] for g in got) and all(g["may"] for g in got if g["alike"])


def test_a_chain_of_edits_stays_one_group(spark, monkeypatch):
    """Neighbours are alike, the ends are not; every pair of neighbours counts."""
    words = [f"w{k}" for k in range(200)]
    texts = {k: " ".join([f"v{j}" for j in range(12 * k)] + words[12 * k :]) for k in range(17)}
    assert {(a, b) for a, b, _ in linked(texts)} == set(itertools.pairwise(range(17)))
    kept, _ = compared(spark, monkeypatch, texts)
    assert kept == {0}
