"""The operators against brute force on hand-made rows: nulls, empty and long texts, ties, repeated rows, empty tables."""

import hashlib
import random
import re
import zlib
from itertools import combinations

import numpy as np
import pytest

from lmrel.llm import bpe, jaccard, media, mixing, sharding, substrings, topk, toxicity
from lmrel.llm.boosting import Isotonic

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def rows():
    r = random.Random(5)
    vocabulary = [f"w{i}" for i in range(300)]
    base = [" ".join(r.choice(vocabulary) for _ in range(r.randint(1, 120))) for _ in range(30)]
    texts = [*base, *base[:6]]
    for t in base[:12]:
        w = t.split()
        for _ in range(2):
            v = list(w)
            v[r.randrange(len(v))] = "edit"
            texts.append("  ".join(v).upper() if r.random() < 0.3 else "\n".join(v))
    passage = " ".join(r.choice(vocabulary) for _ in range(40))
    texts += [f"{base[i]} {passage} tail{i}" for i in range(8)]
    texts += [None, "", "   ", "one", "One", "é" * 50 + " ß  \t x", "long " * 3000, "x" * 3000]
    out = [(i, t, "en", "src%d" % (i % 3) if i % 7 else None, len(t or "")) for i, t in enumerate(texts)]
    return [*out, out[3], (None, base[0], "en", "src1", 3)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.mark.parametrize("class_shingles", [jaccard.CLASS_SHINGLES, 150, 40])
def test_jaccard_classes(docs, rows, none, class_shingles, monkeypatch):
    monkeypatch.setattr(jaccard, "CLASS_SHINGLES", class_shingles)
    monkeypatch.setattr(jaccard, "HUBS", 16 if class_shingles > 40 else 1)

    def shingles(t):
        w = WORD.findall("".join(c.lower() if c in "ABCDEFGHIJKLMNOPQRSTUVWXYZ" else c for c in t or ""))
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    sets = {i: shingles(t) for i, t, *_ in rows if i is not None}
    root = {i: i for i in sets}
    find = lambda i: i if root[i] == i else find(root[i])
    for a, b in combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if sets[a] and sets[b] and 100 * both >= 75 * len(sets[a] | sets[b]):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    got = jaccard.near_duplicate_classes(docs).collect()
    assert len(got) == len(rows)
    for r in got:
        if r.doc_id is not None:
            assert (r.n_shingles, r.component_id) == (len(sets[r.doc_id]), find(r.doc_id))
        else:
            assert r.component_id is None
    kept = [r.doc_id for r in jaccard.one_of_each_class(docs).collect()]
    assert sorted(x for x in kept if x is not None) == sorted({find(i) for i in sets})
    assert jaccard.near_duplicate_classes(none).count() == 0


def test_bound_never_below_overlap():
    r = np.random.default_rng(0)
    for n in (3, 40, 400, 3000):
        a = np.unique(r.integers(0, 2**63, n, dtype=np.uint64))
        b = np.unique(np.concatenate([a[: n // 2], r.integers(0, 2**63, n // 2 + 1, dtype=np.uint64)]))
        g = min(jaccard.groups_of(len(a)), jaccard.groups_of(len(b)))
        p = jaccard.folded([jaccard.point(a), jaccard.point(b)], g)
        assert np.minimum(p[0], p[1]).sum() >= len(np.intersect1d(a, b))


def test_tree_compares_at_the_groups_of_the_smaller_set():
    r = np.random.default_rng(3)
    sets = [np.unique(r.integers(0, 2**63, n, dtype=np.uint64)) for n in [60] * 3 + [1000] * 70 + [1010] * 70 + [4000] * 9]
    sets += [np.concatenate([sets[-1][:-100], sets[0]]), sets[5][:-60]]
    n, points = np.array([len(s) for s in sets]), [jaccard.point(s) for s in sets]
    bound = {(a, b) for a, b in combinations(range(len(sets)), 2) if 7 * int(np.minimum(*jaccard.folded([points[a], points[b]], min(len(points[a]), len(points[b]))).astype(int)).sum()) >= 3 * (n[a] + n[b])}
    assert {tuple(sorted(map(int, x))) for x in jaccard.tree_links(n, points)} == bound == {(151, 152), (5, 153)}
    assert jaccard.tree_links(n, points, None, np.where(np.arange(len(n)) >= 151, 151, np.arange(len(n)))) != []


def test_tree_finds_what_all_pairs_find(monkeypatch):
    monkeypatch.setattr(jaccard, "TILE", 3)
    monkeypatch.setattr(jaccard, "FANOUT", 2)
    r = np.random.default_rng(11)
    sets = []
    for size in (1, 7, 90, 260, 300, 700):
        base = np.unique(r.integers(0, 2**63, size, dtype=np.uint64))
        for cut in (0, 0.1, 0.2, 0.3, 0.6):
            drop = int(len(base) * cut)
            for _ in range(4):
                sets.append(np.unique(np.concatenate([r.permutation(base)[drop:], r.integers(0, 2**63, drop // 2, dtype=np.uint64)])))
    sets = [sets[i] for i in r.permutation(len(sets))]
    n, points = np.array([len(s) for s in sets]), [jaccard.point(s) for s in sets]

    def exact(a, others):
        return np.array([100 * len(np.intersect1d(sets[a], sets[b])) >= 75 * len(np.union1d(sets[a], sets[b])) for b in others])

    def classes(links):
        forest = jaccard.Forest(len(sets))
        for a, b in links:
            forest.join(int(a), int(b))
        return forest.roots(np.arange(len(sets))).tolist()

    pairs = list(combinations(range(len(sets)), 2))
    assert classes(jaccard.tree_links(n, points, exact)) == classes([p for p in pairs if exact(p[0], [p[1]])[0]])
    bound = [(a, b) for a, b in pairs if 7 * int(np.minimum(*jaccard.folded([points[a], points[b]], min(len(points[a]), len(points[b]))).astype(int)).sum()) >= 3 * (n[a] + n[b])]
    assert classes(jaccard.tree_links(n, points)) == classes(bound)


def test_corners_rule_out_no_link():
    r = np.random.default_rng(4)
    for _ in range(200):
        x, y = (np.array([r.poisson(4, 64) + common for _ in range(3)]) for common in [r.poisson(2, 64)] * 2)
        n = np.concatenate([x.sum(axis=1), y.sum(axis=1)])
        a, b = jaccard.Box(n, np.arange(3), x), jaccard.Box(n, np.arange(3, 6), y)
        linked = any(7 * np.minimum(u, v).sum() >= 3 * (u.sum() + v.sum()) for u in x for v in y)
        assert jaccard.may_link([a], [b], 64)[0, 0] or not linked
        folded = any(7 * np.minimum(jaccard.fold(u, 32), jaccard.fold(v, 32)).sum() >= 3 * (u.sum() + v.sum()) for u in x for v in y)
        assert jaccard.may_link([a], [b], 32)[0, 0] or not folded


def test_substring_dedup(docs, rows, none):
    texts = {i: WORD.findall(t or "") for i, t, *_ in rows if i is not None}
    least = {}
    for i in sorted(texts):
        for p in range(len(texts[i]) - 12):
            least.setdefault(tuple(texts[i][p : p + 13]), i)
    for r in substrings.digests(docs).collect():
        if r.doc_id is None:
            assert r.n_removed == 0
            continue
        w, gone = texts[r.doc_id], set()
        for p in range(len(w) - 12):
            if least[tuple(w[p : p + 13])] < r.doc_id:
                gone |= set(range(p, p + 13))
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        assert (r.n_words, r.n_removed, r.kept_sha256) == (len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest())
    assert substrings.digests(none).count() == 0
    assert substrings.without_repeats(docs).columns == docs.columns


def test_bpe_equals_library(docs, rows, none):
    tiktoken = pytest.importorskip("tiktoken")
    import public_tokenizers

    own = bpe.codec()
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=own.ranks, special_tokens={})
    r = random.Random(2)
    more = ["a" * 700, "".join(r.choice("abcdetionsh") for _ in range(2000)), " \n \t x  y z　 w", "\x1c\x00 a", "'s don't  I'll", "日本語 テキスト", "".join(chr(r.choice([32, 10, 97, 49, 0x4E00, 0x1F600])) for _ in range(3000))]
    for t in [*(t or "" for _, t, *_ in rows), *more]:
        ids = own.encode(t)
        assert np.frombuffer(ids, "<u4").tolist() == library.encode_ordinary(t)
        assert own.decode(ids) == t.encode()
    assert {x.doc_id: x.n_tokens for x in bpe.digests(docs).collect()}[0] == len(library.encode_ordinary(rows[0][1]))
    assert all(x.exact for x in bpe.token_ids(docs).collect()) and bpe.digests(none).count() == 0


def test_media_round_trip(spark, docs, rows, none, tmp_path):
    recipe = media.recipes(docs)
    back = {r.media: r for r in media.rebuilt(*media.chunk_store(docs, recipe)).collect()}
    for r in recipe.collect():
        text = next((t for i, t, *_ in rows if i == r.doc_id), "") or ""
        payload = media.padded(text.encode())
        got = back[r.media]
        assert len(payload) % 64 == 0 and payload and r.n_bytes == len(text.encode())
        assert (got.payload_sha256, got.tail_crc32) == (hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
    media.write_store(docs, str(tmp_path))
    assert media.read_store(spark, str(tmp_path)).count() == len(back)
    assert media.rebuilt(*media.chunk_store(none, media.recipes(none))).count() == 0
    data = bytes(random.Random(1).randbytes(60_000))
    a, b = media.chunked(data), media.chunked(data[:100] + b"!" + data[100:])
    assert b"".join(a) == data and len(set(a) & set(b)) >= len(a) - 3


def test_mixing(docs, rows, none):
    out = mixing.plan(docs.withColumn("mix_size", mixing.n_words(docs["text"]))).collect()
    taken, target, size = {}, {}, {}
    for r in out:
        assert 0 <= r.mix_taken <= 3 * r.mix_size
        taken[r.source] = taken.get(r.source, 0) + r.mix_taken
        size[r.source] = size.get(r.source, 0) + r.mix_size
        target[r.source] = r.mix_target
    assert abs(sum(target.values()) - sum(size.values())) < 1e-6
    assert all(abs(taken[s] - target[s]) <= 0.02 * target[s] + 8 for s in taken)
    words = sum(len(WORD.findall(r.text or "")) for r in mixing.mixed_documents(docs).collect())
    assert words == sum(taken.values()) and mixing.mixed_documents(none).count() == 0
    assert mixing.apportion([5, 2, 1], 8) == [5, 2, 1] and mixing.apportion([53, 24, 23], 7) == [3, 2, 2]
    r = random.Random(3)
    for _ in range(60):
        w, seats = [r.randint(0, 60) for _ in range(r.randint(1, 6))], r.randint(0, 40)
        most, held = [r.randint(0, 20) for _ in w], [0] * len(w)
        for _ in range(min(seats, sum(m for m, x in zip(most, w) if x))):
            i = max((i for i in range(len(w)) if w[i] and held[i] < most[i]), key=lambda i: (w[i] / (2 * held[i] + 1), -i))
            held[i] += 1
        assert mixing.apportion(w, seats, most) == held


def test_sharding(spark, docs, rows, none, tmp_path):
    out, slot_map = sharding.sharded(docs, shards=5)
    got = out.collect()
    assert len(got) == len(rows)
    for s in range(5):
        assert sorted(r.slot for r in got if r.shard == s) == list(range(sum(r.shard == s for r in got)))
    size = [0] * sharding.SLOTS
    for r in got:
        size[r.virtual_slot] += r.size
    grown = slot_map.grown(size)
    assert grown.version == 2 and all(grown.owner[i] == 5 for i in slot_map.moved(grown))
    slot_map.save(spark, str(tmp_path))
    assert sharding.SlotMap.load(spark, str(tmp_path), 1) == slot_map
    assert sharding.sharded(none)[0].count() == 0


def test_top_k(spark):
    r = np.random.default_rng(1)
    vectors = [(i, [float(x) for x in r.normal(size=8)]) for i in range(180)]
    vectors += [(i, [0.5] * 8) for i in range(200, 260)] + [(300, None), (301, [float("nan")] * 8), (302, [None] * 8), (303, [float("inf")] * 8), (304, [])]
    df = spark.createDataFrame(vectors, "vec_id long, embedding array<double>")
    q = {i: np.floor(256 * np.array(v)) for i, v in vectors if i < 300}
    got = {}
    for x in topk.exact_top_k(df, df.where("vec_id % 50 = 0")).collect():
        got.setdefault(x.query_id, []).append((x["rank"], x.vec_id, x.score))
    for i in (0, 50, 100, 150, 200, 250):
        best = sorted(((-int(q[i] @ q[j]), j) for j in q if j != i))[:5]
        assert sorted(got[i]) == [(k + 1, j, -s) for k, (s, j) in enumerate(best)]
    assert set(got) == {0, 50, 100, 150, 200, 250}
    assert topk.exact_top_k(df.limit(0), df.limit(0)).count() == 0


def test_toxicity(spark, none):
    r = random.Random(4)
    vocabulary = [f"word{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(200)]
    data, labels = [], []
    for i in range(700):
        w, bad = [r.choice(vocabulary) for _ in range(r.randint(5, 60))], i % 5 == 0
        for _ in range(2 * bad):
            w.insert(r.randrange(len(w)), r.choice(["grumlak", "zorble"]) + r.choice(["", "en", "ity"]))
        data.append((i, " ".join(w), "en", "s", 0))
        labels.append((i, 1, int(bad)))
    data += [(900, None, "en", "s", 0), (901, "", "en", "s", 0), (None, "x", "en", "s", 0)]
    docs, known = spark.createDataFrame(data, SCHEMA), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    out = {x.doc_id: x for x in toxicity.scored(docs, toxicity.fit(docs, known)).collect()}
    held = [x for i, x in out.items() if i is not None and i < 700 and x.held_out]
    assert held and sum(x.predicted == (x.doc_id % 5 == 0) for x in held) >= 0.95 * len(held)
    assert all(0 <= x.score <= 1 and x.predicted == (x.score >= 0.5) for x in out.values()) and out[901].predicted == 0
    assert all(x.held_out == (zlib.crc32(str(x.doc_id).encode()) % 5 == 0) for i, x in out.items() if i is not None)
    assert toxicity.scored(none, toxicity.fit(none, known)).count() == 0
    fit = Isotonic().fit(np.array([1.0, 2, 3, 4]), np.array([0.0, 1, 0, 1]), np.ones(4))
    assert list(fit(np.array([1.0, 2.5, 4.0]))) == [0.0, 0.5, 1.0]


def test_pipeline(spark, docs, tmp_path):
    import corpus_pipeline

    labels = spark.createDataFrame([(i, 1, 0) for i in range(20)], "doc_id long, quality int, toxic int")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    now = docs
    for name, stage in corpus_pipeline.STAGES:
        now = stage(spark, now, str(tmp_path))
        now.write.parquet(f"{tmp_path}/{name}")
        now = spark.read.parquet(f"{tmp_path}/{name}")
        assert name == "byte_pair_encoding" or now.columns == docs.columns
    assert now.count() > 20 and now.where("NOT exact").count() == 0
