"""Windows that occur twice in one document, met by a smaller document of another batch."""

import hashlib

from lmrel.llm import substrings


def test_every_place_of_a_repeated_window(spark):
    passage = " ".join(f"p{i}" for i in range(20))
    texts = {1: f"one {passage} two", 2: f"three {passage} four {passage} five {passage}", 3: "long " * 40, 4: "x " + "long " * 60}
    old = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1")
    try:
        got = {r.doc_id: r for r in substrings.digests(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", old)
    assert [got[i].n_removed for i in sorted(texts)] == [0, 60, 0, 60]
    assert got[2].kept_sha256 == hashlib.sha256(b"three four five").hexdigest()
