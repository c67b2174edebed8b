"""Scores prefer text like the corpus; empty and null texts and empty tables have defined results."""

import random

from lmrel.llm.scoring import fit, scored


def test_scores(spark):
    r = random.Random(1)
    regular = lambda: " ".join("the cat sat on a mat".split() * 12)
    rows = [(i, regular()) for i in range(250)]
    shuffled = regular().split()
    r.shuffle(shuffled)
    asked = spark.createDataFrame([(0, regular()), (1, " ".join(shuffled)), (2, None), (3, ""), (4, "x")], "doc_id long, text string")
    corpus = spark.createDataFrame(rows, "doc_id long, text string").coalesce(2)
    out = {x.doc_id: x for x in scored(asked, fit(corpus)).collect()}
    assert out[0].n_words == out[1].n_words == 72 and out[0].log_likelihood > out[1].log_likelihood
    assert out[2].log_likelihood == 0 and out[3]["mean"] is None and out[4].n_words == 1
    assert scored(asked.limit(0), fit(corpus.limit(0))).count() == 0
