"""Clashing columns, repeated ids, other patterns, groups of copies, worker memory, and the stages against brute force."""

import random
import re
import time
from collections import Counter
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from lmrel.llm import bpe, common, jaccard, media, mixing, scoring, sharding, substrings, toxicity

WORD = re.compile(r"[^\x20\x09-\x0D]+")
CLASHES = ["marks", "of", "marked_id", "marked_of", "mix_size", "mix_text", "mix_at", "mix_shard", "source_r", "component_id", "n", "text_crc32", "size", "score", "held_out", "ids", "chunks", "_marks"]


def lines(prefix: str, n: int) -> str:
    return " ".join(f"{prefix}{i}" for i in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(1, lines("a", 40), "s"), (1, lines("b", 40), "s"), (2, "head " + lines("b", 40), None), (3, None, "t"), (4, "", "t"), (5, lines("a", 40), "t"), (5, lines("a", 40), "t"), (None, lines("a", 40), "t"), (6, lines("c", 3000), "s")]
    df = spark.createDataFrame([(i, t, "en", s, len(t or "")) for i, t, s in rows], "doc_id long, text string, lang string, source string, n_chars long")
    return df.select("*", *(F.lit(f"kept {c}").alias(c) for c in CLASHES))


def test_columns_of_any_name_are_kept(spark, odd):
    kept = lambda df: all(df.where(F.col(c) != f"kept {c}").count() == 0 for c in CLASHES)
    for f in (substrings.without_repeats, mixing.mixed_documents, jaccard.one_of_each_class):
        out = f(odd)
        assert out.columns == odd.columns and kept(out), f
        assert f(odd.limit(0)).count() == 0
    labels = spark.createDataFrame([(i, 1, i % 2) for i in range(9)], "doc_id long, quality int, toxic int").withColumn("text", F.lit("clash"))
    model = toxicity.fit(odd, labels)
    assert toxicity.scored(odd, model).count() == 9 and kept(toxicity.without_toxic(odd, model, 2.0))
    assert bpe.digests(odd).count() == media.recipes(odd).count() == sharding.sharded(odd, 3)[0].count() == 9
    assert scoring.scored(odd, scoring.fit(odd)).count() == 9
    with pytest.raises(ValueError):
        substrings.marked(odd)
    with pytest.raises(ValueError):
        bpe.token_ids(odd, ("ids",))


def test_every_text_of_a_doc_id_is_judged(odd):
    got = Counter((r.doc_id, r.n_words, r.n_removed) for r in substrings.digests(odd).collect())
    assert got == Counter([(1, 40, 0), (1, 40, 0), (2, 41, 40), (3, 0, 0), (4, 0, 0), (5, 40, 40), (5, 40, 40), (None, 40, 0), (6, 3000, 0)])
    stay = sorted((r.doc_id or 0, r.n_chars) for r in jaccard.one_of_each_class(odd).collect())
    a, b = len(lines("a", 40)), len(lines("b", 40))
    assert stay == sorted([(1, a), (1, b), (3, 0), (4, 0), (0, a), (6, len(lines("c", 3000)))])


@pytest.mark.parametrize("hot", [0, 1, 3])
def test_hot_anchors_are_dealt_by_window(spark, monkeypatch, hot):
    r = random.Random(hot)
    opening = lines("o", 6)
    texts = [(i, f"{lines(f'x{r.randrange(6)}_', 9)} {opening} {lines(f'y{r.randrange(6)}_', 15)} {opening} {lines(f'z{i}_', 4)}") for i in range(60)]
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(5)
    old = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        want = {x.doc_id: x.kept_sha256 for x in substrings.digests(docs).collect()}
        monkeypatch.setattr(substrings, "HOT", hot)
        got = {x.doc_id: x.kept_sha256 for x in substrings.digests(docs).collect()}
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", old)
    assert got == want and len(set(want.values())) > 3


def test_other_patterns_as_the_library(spark):
    tiktoken = pytest.importorskip("tiktoken")
    texts = ["a b  c", " don't stop 12345", "x " * 300, "tab\tand\nline", "", "ünï cödé 日本"]
    for pattern in (r"\S+\s*", r"[a-z]+|\s", r"(?:'s)|\p{L}+| ?[^\s\p{L}]+|\s+"):
        own = bpe.codec(None, pattern)
        library = tiktoken.Encoding("x", pat_str=pattern, mergeable_ranks=own.ranks, special_tokens={})
        for t in texts:
            assert np.frombuffer(own.encode(t), "<u4").tolist() == library.encode_ordinary(t)


def test_obfuscated_insults_of_any_length():
    word = "i" + "." * 60 + "d.i.0.t" + "-" * 30 + "?"
    data = np.frombuffer(word.encode(), np.uint8)
    x = toxicity.featured(data, np.array([0, len(data)]), np.zeros(0, np.uint64), np.zeros(0))
    assert x[0][toxicity.NAMES.index("hidden_hits")] == 1


def test_copies_are_dealt_over_all_shards(spark):
    rows = [(i, "copy " * 40 if i % 3 == 0 else f"own text {i} " * (15 + i % 5)) for i in range(6000)]
    got = sharding.sharded(spark.createDataFrame(rows, "doc_id long, text string"), 6)[0].collect()
    size = Counter()
    for r in got:
        size[r.shard] += r.size
    assert max(size.values()) < 1.02 * min(size.values())
    assert {r.shard for r in got if r.doc_id % 3 == 0} == set(range(6))


def test_many_shards_are_apportioned_quickly():
    r, began = random.Random(1), time.perf_counter()
    assert sum(mixing.apportion([r.randint(1, 10**9) for _ in range(4096)], 10**6)) == 10**6
    assert time.perf_counter() - began < 5


def test_quotas_join_without_a_broadcast(spark, monkeypatch):
    docs = spark.createDataFrame([(i, f"{lines('w', i % 9)}", f"s{i % 50}" if i % 50 else None) for i in range(900)], "doc_id long, text string, source string")
    sized = docs.select("doc_id", "source", mixing.n_words(F.col("text")).alias("mix_size"))
    want = sorted((r.doc_id, r.mix_taken) for r in mixing.plan(sized).collect())
    monkeypatch.setattr(mixing, "BROADCAST_ROWS", 3)
    assert sorted((r.doc_id, r.mix_taken) for r in mixing.plan(sized).collect()) == want


def test_a_cluster_needs_a_shared_folder():
    class Session:
        class sparkContext:  # noqa: N801
            master = "yarn"

            class _jsc:  # noqa: N801
                sc = staticmethod(lambda: type("S", (), {"getCheckpointDir": staticmethod(lambda: type("D", (), {"isEmpty": staticmethod(lambda: True)}))}))

            getConf = staticmethod(lambda: {})

    with pytest.raises(RuntimeError):
        common.reliable(type("DF", (), {"sparkSession": Session}))


def test_stages_against_brute_force(spark, tmp_path):
    tiktoken = pytest.importorskip("tiktoken")
    r = random.Random(9)
    vocabulary = [f"w{i}" for i in range(400)]
    base = [" ".join(r.choice(vocabulary) for _ in range(r.randint(20, 90))) for _ in range(25)]
    near = [" ".join(["edit", *t.split()[1:]]) for t in base[:8]]
    shared = " ".join(r.choice(vocabulary) for _ in range(60))
    texts = [*base, *base[:4], *near, *(f"{' '.join(r.choice(vocabulary) for _ in range(70))} {shared}" for _ in range(5)), None, "", "  "]
    docs = spark.createDataFrame([(i, t, "en", f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    spark.createDataFrame([(i, 1, 0) for i in range(20)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    seen = {}
    now = docs
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, now, str(tmp_path)).write.parquet(f"{tmp_path}/{name}")
        now = spark.read.parquet(f"{tmp_path}/{name}")
        seen[name] = [row.asDict() for row in now.collect()]
    assert len(seen["toxicity"]) == len(texts)  # labels of one class: the fixed lexicon, no insults here

    def shingles(t):
        w = WORD.findall((t or "").lower())
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    sets, root = [shingles(t) for t in texts], list(range(len(texts)))
    find = lambda i: i if root[i] == i else find(root[i])
    for a, b in combinations(range(len(texts)), 2):
        if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    kept = sorted({find(i) for i in range(len(texts))})
    assert sorted(x["doc_id"] for x in seen["near_duplicates"]) == kept
    words, least, cut = {i: WORD.findall(texts[i] or "") for i in kept}, {}, {}
    for i in kept:
        for p in range(len(words[i]) - 12):
            least.setdefault(tuple(words[i][p : p + 13]), i)
    for i in kept:
        gone = {q for p in range(len(words[i]) - 12) if least[tuple(words[i][p : p + 13])] < i for q in range(p, p + 13)}
        if not gone or len(gone) < len(words[i]):
            cut[i] = " ".join(w for q, w in enumerate(words[i]) if q not in gone) if gone else texts[i]
    assert {x["doc_id"]: x["text"] for x in seen["substring_dedup"]} == cut
    goal = mixing.targets({s: sum(len(WORD.findall(cut[i] or "")) for i in cut if i % 3 == int(s[1])) for s in ("s0", "s1", "s2")})
    taken = Counter()
    for x in seen["mixing"]:
        taken[x["source"]] += len(WORD.findall(x["text"] or ""))
        assert set(WORD.findall(x["text"] or "")) <= set(WORD.findall(cut[x["doc_id"]] or ""))
    assert all(abs(taken[s] - goal[s]) <= 0.02 * goal[s] + 8 for s in goal)
    library = tiktoken.Encoding("x", pat_str=bpe.codec().pattern.pattern, mergeable_ranks=bpe.codec().ranks, special_tokens={})
    assert Counter((x["doc_id"], tuple(x["ids"])) for x in seen["byte_pair_encoding"]) == Counter((x["doc_id"], tuple(library.encode_ordinary(x["text"] or ""))) for x in seen["mixing"])
