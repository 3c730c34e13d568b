"""The pipeline's near-duplicate stage against brute force on pairs of known similarity."""

import itertools
import random
import re

import corpus_pipeline


def shingles(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()


def likeness(a, b):
    return len(a & b) / len(a | b) if a | b else 1.0


def linked(texts):
    sets = {k: shingles(t) for k, t in texts.items()}
    return [(a, b, s) for a, b in itertools.combinations(sorted(sets), 2) if (s := likeness(sets[a], sets[b])) >= 0.8]


def test_pairs_from_08_on_lose_one(spark):
    r, texts = random.Random(6), {}
    for k in range(300):
        words = [f"w{r.randrange(5000)}" for _ in range(r.choice([15, 60, 200, 400]))]
        texts[2 * k] = " ".join(words)
        for _ in range(r.randrange(1, 1 + max(2, len(words) // 25))):
            words[r.randrange(len(words))] = "changed"
        texts[2 * k + 1] = " ".join(words)
    pairs = linked(texts)
    assert sum(s < 0.9 for *_, s in pairs) > 60
    docs = spark.createDataFrame([(k, t, "en", "s", len(t)) for k, t in texts.items()], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    kept = {d["doc_id"] for d in corpus_pipeline.one_of_each_group(spark, docs, "").collect()}
    assert sum(b not in kept for _, b, _ in pairs) >= 0.99 * len(pairs)
    assert set(texts) - kept <= {b for _, b, _ in pairs}  # nothing below the bound is dropped


def test_nulls_copies_and_ids(spark):
    long = " ".join(f"x{k}" for k in range(50))
    rows = [(3, long), (1, long), (1, long), (1, "other words"), (None, long), (None, "lonely row"), (4, None), (5, " ")]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    kept = corpus_pipeline.one_of_each_group(spark, docs, "")
    assert kept.columns == docs.columns
    assert sorted(((d["doc_id"], d["text"]) for d in kept.collect()), key=str) == sorted([(1, long), (1, "other words"), (None, "lonely row"), (4, None)], key=str)
    assert corpus_pipeline.one_of_each_group(spark, docs.limit(0), "").count() == 0
