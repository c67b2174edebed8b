"""The scores are probabilities of words, not of classes, and the network learns on through all batches."""

import math
import random

from lmrel.llm.scoring import fit, scored


def test_words_sum_to_one(spark):
    r = random.Random(2)
    names = [f"w{i}" for i in range(900)]
    texts = [" ".join(names[int(900 * r.random() ** 3)] for _ in range(30)) for _ in range(200)]
    words = sorted({w for t in texts for w in t.split()})
    model = fit(spark.createDataFrame([(t,) for t in texts], "text string").repartition(3))
    once = sum(sum(t.split().count(w) for t in texts) == 1 for w in words)
    assert once > 5 and len(model.vocabulary.words) == len(words) - once > 256
    asked = spark.createDataFrame(list(enumerate([*words, "never-seen"])), "doc_id long, text string")
    got = {x.doc_id: x.log_likelihood for x in scored(asked, model).collect()}
    assert abs(sum(map(math.exp, got.values())) - 1) < 1e-3
    assert got[len(words)] < got[words.index("w0")] - 3


def test_batches_train_one_network(spark):
    corpus = spark.createDataFrame([(i, " ".join("the cat sat on a mat".split() * 12) + f" n{i}") for i in range(120)], "doc_id long, text string").coalesce(1)
    old = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1")
    try:
        out = scored(spark.createDataFrame([(0, "the cat sat on a mat " * 12)], "doc_id long, text string"), fit(corpus)).first()
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", old)
    assert out["mean"] > -0.5
