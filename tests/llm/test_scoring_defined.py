"""The scores follow from the rows alone, tell more than counts, and add up as a brute-force sum does."""

import math
import random
from collections import Counter

import numpy as np
import pytest

from lmrel.llm import scoring
from lmrel.llm.grams import word_hashes


def prose(r: random.Random, n: int) -> str:
    """Words of which each half decides the next."""
    out, w = [], r.randrange(40)
    for _ in range(n):
        out.append(f"w{w}" if r.random() < 0.97 else f"rare{r.randrange(4000)}")
        w = (3 * w + r.randrange(3)) % 40
    return " ".join(out)


@pytest.fixture(scope="module")
def corpus(spark):
    r = random.Random(1)
    rows = [(i if i % 97 else None, prose(r, r.randint(1, 400))) for i in range(400)] + [(900, None), (901, ""), (902, "solo"), (903, prose(r, 30000))]
    rows += [rows[5], rows[5], (904, rows[6][1])]
    return spark.createDataFrame(rows, "doc_id long, text string").cache()


def close(a, b) -> bool:
    key = lambda r: (r.doc_id or -1, r.n_words, r.log_likelihood)
    return len(a) == len(b) and all((x.doc_id, x.n_words) == (y.doc_id, y.n_words) and abs(x.log_likelihood - y.log_likelihood) <= 1e-6 * max(1, abs(x.log_likelihood)) for x, y in zip(sorted(a, key=key), sorted(b, key=key)))


def test_neither_batches_nor_partitions_matter(spark, corpus, monkeypatch):
    monkeypatch.setattr(scoring, "SHARD_BYTES", 20_000)  # several shards a round
    run = lambda df: scoring.scored(df, scoring.fit(df)).collect()
    want = run(corpus.coalesce(1))
    assert close(run(corpus.repartition(7)), want)
    old = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch"), spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "13")
    spark.conf.set("spark.sql.shuffle.partitions", "3")
    try:
        assert close(run(corpus), want)
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", old[0])
        spark.conf.set("spark.sql.shuffle.partitions", old[1])


@pytest.mark.parametrize("frequent", [scoring.FREQUENT, 100])
def test_a_brute_force_sum(corpus, monkeypatch, frequent):
    monkeypatch.setattr(scoring, "FREQUENT", frequent)  # with few of them the other counts come by the join
    model = scoring.fit(corpus)
    texts = {r.doc_id: r.text or "" for r in corpus.collect() if r.doc_id is not None}
    n = Counter(w for r in corpus.collect() for w in (r.text or "").split())
    once = sum(c == 1 for c in n.values())
    assert len(model.vocabulary.words) == len(n) - once and model.vocabulary.deal.once == once

    def print_of(w: str) -> np.uint64:
        data = np.frombuffer(w.encode(), np.uint8)
        return word_hashes(data, np.array([0]), np.array([len(data)]), True)[0]

    names = sorted(n)
    kinds = dict(zip(names, model.vocabulary.deal.kind(np.array([print_of(w) for w in names]), np.array([n[w] for w in names])).tolist()))
    mass = Counter()
    for w in names:
        mass[kinds[w]] += n[w] * (n[w] > 1)
    inputs, top, first, out, second = (x.astype(float) for x in scoring._parts(model.flat))
    each = scoring.CLASSES // scoring.BRANCHES
    got = {r.doc_id: r.log_likelihood for r in scoring.scored(corpus, model).collect() if r.doc_id is not None}
    for i in (1, 2, 3, 902, 900):
        ks, total = [kinds[w] for w in texts[i].split()], 0.0
        for p, w in enumerate(texts[i].split()):
            h = sum(inputs[j][ks[p + d] if 0 <= p + d < len(ks) else scoring.CLASSES] for j, d in enumerate(scoring.SIDES))
            h = h / (1 + abs(h))
            g, m = divmod(ks[p], each)
            a, b = top @ h + first, out[g] @ h + second[g]
            share = math.log(n[w] / mass[kinds[w]]) if n[w] > 1 else -math.log(once + 1)
            total += a[g] - np.log(np.exp(a).sum()) + b[m] - np.log(np.exp(b).sum()) + share
        assert got[i] == pytest.approx(total, rel=1e-4, abs=1e-3)


def test_both_sides_tell_more_than_counts(spark):
    r = random.Random(4)
    train = spark.createDataFrame([(i, prose(r, 200)) for i in range(500)], "doc_id long, text string")
    held = [prose(r, 200) for _ in range(60)]
    model = scoring.fit(train)
    rows = scoring.scored(spark.createDataFrame(list(enumerate(held)), "doc_id long, text string"), model).collect()
    n = Counter(w for x in train.collect() for w in x.text.split())
    total, once = sum(n.values()), sum(c == 1 for c in n.values())
    seen = [n[w] / total if n[w] > 1 else once / total / (once + 1) for t in held for w in t.split()]
    unigram = sum(map(math.log, seen)) / len(seen)
    assert sum(x.log_likelihood for x in rows) / sum(x.n_words for x in rows) > unigram + 0.5


def test_repeats_ties_and_long_texts(corpus):
    got = scoring.scored(corpus, scoring.fit(corpus)).collect()
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
    assert len(got) == corpus.count() and len(by[5]) == 3 and len({(x.n_words, x.log_likelihood) for x in by[5]}) == 1
    assert by[904][0].log_likelihood == by[6][0].log_likelihood and by[903][0].n_words == 30000
    assert by[900][0].log_likelihood == by[901][0].log_likelihood == 0 and by[900][0]["mean"] is None
    assert all(np.isfinite(x.log_likelihood) and x.log_likelihood <= 0 for x in got)
