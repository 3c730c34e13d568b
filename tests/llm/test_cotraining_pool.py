"""Co-training looks at every unlabelled document, not at a sample of them."""

import numpy as np
from pyspark.sql import functions as F

from spanweave.llm import cotraining


def test_whole_table_teaches_and_bins(spark, monkeypatch):
    ids = spark.range(10_000).orderBy(F.xxhash64("id", F.lit("pool")), "id")
    first = {r["id"] for r in ids.limit(4000).collect()}  # what a sample by this hash sees
    rare = sorted(set(range(10_000)) - first)[:3]
    row = lambda k: "zq#" * 80 if k in rare else f"plain words number {k} here" if k in first else f"plain words number {k} here and on " * 9
    rows = [(k, row(k), "en", "s") for k in range(10_000)]
    rows += [(20_000 + k, f"plain words number {k} there" if k % 2 else "zq#" * (40 + k), "en", "s") for k in range(60)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string").repartition(4)
    labels = spark.createDataFrame([(20_000 + k, k % 2) for k in range(60)], "doc_id bigint, quality int")
    keys = {r["key"] for r in cotraining.featured(docs.where(F.col("doc_id").isin(rare))).collect()}
    chosen, own = [], cotraining.most_sure
    monkeypatch.setattr(cotraining, "most_sure", lambda *a: chosen.append(own(*a)) or chosen[-1])
    model = cotraining.fit(docs, labels)
    assert keys <= {k for found in chosen for _, k, label in found if label == 0}
    sizes = np.quantile([np.log1p(len(t)) for _, t, *_ in rows], np.linspace(0, 1, cotraining.BINS + 2)[1:-1])
    assert np.allclose(model.edges[0], sizes, atol=0.05)
    assert cotraining.LABELLED == 6000 and cotraining.EACH_ROUND == 300
