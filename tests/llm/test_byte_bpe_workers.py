"""Encoders of byte-level BPE: one for each worker, freed with its last use; texts cross the borders of batches whole."""

import gc
import os
import weakref

import public_tokenizers as P
import pyarrow as pa

from spanweave.llm import byte_bpe
from spanweave.llm.shared import BATCH_ROWS

BYTE_BPE = P.path("byte_bpe_multi_50k.tiktoken")


def test_an_encoder_goes_with_its_last_use():
    gc.disable()
    try:
        bpe = byte_bpe.ByteBpe(BYTE_BPE, P.PATTERN)
        assert bpe.decode(bpe.encode("some words, some more")) == b"some words, some more"
        gone = weakref.ref(bpe)
        del bpe
        assert gone() is None
    finally:
        gc.enable()


def test_tasks_of_a_worker_share_its_encoder(spark):
    docs = spark.range(240, numPartitions=24).selectExpr("id AS doc_id", "concat('text ', id) AS text")
    assert byte_bpe.bpe_round_trip(docs, BYTE_BPE, P.PATTERN).count() == 240

    def made(batches):
        for batch in batches:
            yield pa.RecordBatch.from_pydict({"pid": [os.getpid()], "made": [byte_bpe.worker_encoder.cache_info().misses]})

    rows = spark.range(24, numPartitions=24).mapInArrow(made, "pid bigint, made bigint").collect()
    assert {r["made"] for r in rows} <= {0, 1} and any(r["made"] for r in rows)


def test_texts_at_the_borders_of_batches(spark):
    import tiktoken

    encoding = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=byte_bpe.read_ranks(BYTE_BPE), special_tokens={})
    texts = {i: None if i % 97 == 0 else f"row {i} of ä few " * (i % 5) for i in range(2 * BATCH_ROWS + 7)}
    texts |= {5: "long größe " * 200_000, 6: "after ", BATCH_ROWS - 1: "last of a batch " * 70_000, BATCH_ROWS: "first of a batch"}
    docs = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string").coalesce(1)
    out = {r["doc_id"]: (list(r["token_ids"]), bytes(r["decoded"])) for r in byte_bpe.bpe_round_trip(docs, BYTE_BPE, P.PATTERN).collect()}
    assert out == {i: (encoding.encode_ordinary(t or ""), (t or "").encode()) for i, t in texts.items()}
