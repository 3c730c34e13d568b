"""Random runs of every alphabet are found and redacted; words, names and dates are not."""

import random
import string

from pyspark.sql import functions as F

from spanweave.llm import secret_scan


def clean(spark, texts):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    return [r["clean"] for r in secret_scan.scan(df).withColumn("clean", secret_scan.redacted(F.col("text"), F.col("all_spans"))).orderBy("doc_id").collect()]


def test_other_alphabets(spark):
    r = random.Random(8)
    run = lambda letters: "".join(r.choice(letters) for _ in range(36))
    keys = ["k4j2h8s9d7f6g5q1w3e2r4t6y8u0i9o7", "JBSWY3DPEHPK3PXPMZXW6YTBOI2XQ4DF"]
    for letters in (string.digits + string.ascii_lowercase, "234567" + string.ascii_uppercase, string.ascii_letters):
        keys += [run(letters) for _ in range(40)]
    out = clean(spark, [f"key {k} end" for k in keys])
    assert out.count("key [SECRET] end") >= 0.95 * len(keys) and out[:2] == ["key [SECRET] end"] * 2


def test_parts_around_a_base_span(spark):
    key = "Zx9Qw3Er5Ty7Ui1Op2As" + "0123456789abcdef" + "Hj8KzQ4mWv6Xt2Rp9Lb3"
    got = clean(spark, [f"a {key} z", "2024-01-05" + "Zx9Qw3Er5Ty7Ui1Op2AsHj8K", "Zx9Qw3Er5Ty7sampleUi1Op2AsHj8K"])
    assert got == ["a [SECRET][SECRET][SECRET] z", "[SECRET]", "[SECRET]"]


def test_words_stay(spark):
    texts = ["internationalization2024x", "THEQUICKBROWNFOXJUMPS2024", "getElementsByTagNameFromDocument", "2024-01-05T10-20-30", "my-sample-of-words-for-you", "sha-example-key-placeholder-2024", "donaudampfschifffahrtsgesellschaft"]
    assert clean(spark, texts) == texts
