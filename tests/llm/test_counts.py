"""Trees of token counts against full encoding, under random edits."""

import random

import public_tokenizers
import tiktoken
from pyspark.sql import functions as F

from lmrel.llm import bpe
from lmrel.llm.bpe import codec
from lmrel.llm.counts import TokenTree, counted, middle


def library():
    own = bpe.codec()
    return tiktoken.Encoding("x", pat_str=public_tokenizers.PATTERN, mergeable_ranks=own.ranks, special_tokens={})


def test_edits_follow_full_encoding():
    own, full, rng = bpe.codec(), library(), random.Random(3)
    bits = ["word", "  ", " ", "\n", "é", " über", "don't", " 12345", "!?", "\t x", "x" * 9, "　", "日本"]
    for n in (0, 1, 5, 300):
        text = "".join(rng.choice(bits) for _ in range(n))
        tree = TokenTree(text, own)
        for _ in range(60):
            a = rng.randrange(len(text) + 1)
            b = min(len(text), a + rng.choice((0, 1, 7, 400)))
            new = "".join(rng.choice(bits) for _ in range(rng.randrange(4)))
            text = text[:a] + new + text[b:]
            tree.replace(a, b, new)
            assert tree.text == text
            assert tree.total == len(full.encode_ordinary(text))


def test_an_edit_reencodes_its_surroundings_only():
    tree = TokenTree("some words here " * 5000, bpe.codec())
    tree.replace(40000, 40005, " other")
    assert tree.reencoded < 10


def test_counted_rows(spark):
    full, new = library(), " edited text"
    texts = [None, "", " ", "a", "plain words", "x y z " * 400, "é　 日本 " * 30]
    docs = spark.createDataFrame([(i, t, "clash") for i, t in enumerate(texts)], "doc_id long, text string, n_tokens string")
    for row in counted(docs, middle(docs["text"])).collect():
        t = texts[row.doc_id] or ""
        m = len(t) // 2
        assert row.n_tokens == len(full.encode_ordinary(t))
        assert row.n_tokens_edited == len(full.encode_ordinary(t[:m] + new + t[min(len(t), m + 5) :]))
    still = counted(docs, F.lit(None).cast("array<struct<start:long,end:long,new:string>>")).collect()
    assert all(r.n_tokens == r.n_tokens_edited and r.reencoded == 0 for r in still)
    assert counted(docs.limit(0), middle(docs["text"])).count() == 0


def test_edits_equal_full_encoding():
    own, r = codec(), random.Random(7)
    count = lambda t: len(own.encode(t)) // 4
    for text in ("", "a", "  two  spaces \n and\tmore ", " ".join(r.choice(["word", "it's", "42", "x,y", "\n", "é"]) for _ in range(700))):
        tree = TokenTree(text, own)
        assert tree.total == count(text)
        for _ in range(40):
            a = r.randint(0, len(text))
            b = min(len(text), a + r.randint(0, 12))
            new = r.choice(["", " ", "new", " new words here", "\n", "  ", "x" * 30])
            tree.replace(a, b, new)
            text = text[:a] + new + text[b:]
            assert tree.total == count(text)


def test_counts(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (3, "some words"), (3, "some words"), (None, "x")], "doc_id long, text string")
    assert sorted(r.n_tokens for r in counted(docs).collect())[:2] == [0, 0] and counted(docs.limit(0)).count() == 0
