"""Edit-aware token counts: a tree of pre-token segments per document.

A text is cut before spaces that stand before other text, where encoding never looks back.  Blocks
of segments are the leaves of a tree whose nodes hold sums of characters and tokens.  An edit finds
its segments by the character sums, re-encodes them with one segment of context on the left, and
updates the sums on the path.  The trees of many documents are built, and their edits re-encoded,
by one pass of the codec over all their segments.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import SLAB_BYTES, BytePairCodec, codec
from .common import lean, table
from .grams import slabs, strings

BLOCK = 64


def measured(texts: list[str], own: BytePairCodec) -> list[tuple[np.ndarray, np.ndarray]]:
    """Characters and tokens of each segment of each text."""
    raw = [t.encode() for t in texts]
    data, offsets = np.frombuffer(b"".join(raw), dtype=np.uint8), np.concatenate([[0], np.cumsum([len(r) for r in raw], dtype=np.int64)])
    starts, tokens = own.segments(data, offsets.astype(np.int64))
    if not len(starts):
        return [(starts, tokens)] * len(texts)
    chars = np.add.reduceat((data & 0xC0) != 0x80, starts, dtype=np.int64)
    at = np.searchsorted(starts, offsets).tolist()
    return [(chars[a:b], tokens[a:b]) for a, b in zip(at, at[1:])]


class TokenTree:
    """Token count of a text under edits; ``reencoded`` counts the segments encoded after the first build."""

    def __init__(self, text: str, own: BytePairCodec, segments: tuple[np.ndarray, np.ndarray] | None = None):
        self.own, self.reencoded = own, 0
        chars, tokens = segments or measured([text], own)[0]
        ends, at = np.concatenate([[0], np.cumsum(chars)]), range(0, max(1, len(chars)), BLOCK)
        self.blocks = [(text[ends[i] : ends[min(i + BLOCK, len(chars))]], chars[i : i + BLOCK], tokens[i : i + BLOCK]) for i in at]
        self.size = 1 << max(0, (len(self.blocks) - 1).bit_length())
        self.chars, self.tokens = ([0] * (2 * self.size) for _ in range(2))
        if len(chars):
            n = self.size + len(at)
            self.chars[self.size : n], self.tokens[self.size : n] = np.add.reduceat(chars, at).tolist(), np.add.reduceat(tokens, at).tolist()
        for i in range(self.size - 1, 0, -1):
            self._add(i)

    def _add(self, i: int) -> None:
        self.chars[i], self.tokens[i] = self.chars[2 * i] + self.chars[2 * i + 1], self.tokens[2 * i] + self.tokens[2 * i + 1]

    @property
    def total(self) -> int:
        return self.tokens[1]

    @property
    def text(self) -> str:
        return "".join(b[0] for b in self.blocks)

    def _find(self, at: int) -> tuple[int, int, int]:
        """Block and segment that hold a character (the last segment for the end), and where the block begins."""
        i, begin = 1, 0
        at = min(at, self.chars[1] - 1)
        while i < self.size:
            i *= 2
            if at >= begin + self.chars[i]:
                begin += self.chars[i]
                i += 1
        ends = np.cumsum(self.blocks[i - self.size][1])
        return i - self.size, int(np.searchsorted(ends, at - begin, side="right")), begin

    def region(self, start: int, end: int, new: str) -> tuple[int, int, int, int, str]:
        """First and last block and segment that putting ``new`` at start..end touches, and their text afterwards."""
        if not self.chars[1]:
            return 0, 0, 0, 0, new
        b0, k0, begin = self._find(max(0, start - 1))
        if k0:
            k0 -= 1
        elif begin:
            b0, k0, begin = self._find(begin - 1)
        b1, k1, begin1 = self._find(end)
        before = begin + int(self.blocks[b0][1][:k0].sum())
        after = begin1 + int(self.blocks[b1][1][: k1 + 1].sum())
        old = "".join(self.blocks[b][0] for b in range(b0, b1 + 1))
        return b0, k0, b1, k1, old[before - begin : start - begin] + new + old[end - begin : after - begin]

    def put(self, region: tuple[int, int, int, int, str], segments: tuple[np.ndarray, np.ndarray]) -> None:
        """Puts re-encoded segments in the region's place: its first block takes them, later ones keep what is behind."""
        (b0, k0, b1, k1, text), (chars, tokens) = region, segments
        self.reencoded += len(chars)
        first, last = self.blocks[b0], self.blocks[b1]
        head, tail = first[0][: int(first[1][:k0].sum())], last[0][int(last[1][: k1 + 1].sum()) :]
        held = [(head + text, [first[1][:k0], chars], [first[2][:k0], tokens]), *(("", [], []) for _ in range(b0, b1))]
        held[-1] = (held[-1][0] + tail, [*held[-1][1], last[1][k1 + 1 :]], [*held[-1][2], last[2][k1 + 1 :]])
        none = [np.zeros(0, dtype=np.int64)]
        for b, (t, c, n) in enumerate(held, b0):
            self.blocks[b] = t, np.concatenate(c or none), np.concatenate(n or none)
            i = self.size + b
            self.chars[i], self.tokens[i] = len(t), int(self.blocks[b][2].sum())
            while i > 1:
                i //= 2
                self._add(i)

    def replace(self, start: int, end: int, new: str) -> None:
        """Puts ``new`` in place of the characters start..end."""
        region = self.region(start, end, new)
        self.put(region, measured([region[-1]], self.own)[0])


def middle(text: Column, new: str = " edited text", width: int = 5) -> Column:
    """One edit that puts ``new`` in place of ``width`` characters in the middle of a text."""
    size = F.length(F.coalesce(text, F.lit("")))
    at = F.floor(size / 2)
    return F.array(F.struct(at.cast("long").alias("start"), F.least(at + width, size).cast("long").alias("end"), F.lit(new).alias("new")))


def counted(docs: DataFrame, edits: Column | None = None) -> DataFrame:
    """doc_id, n_tokens, n_tokens_edited and reencoded (segments) of every whole text under its ``edits``.

    ``edits`` (by default one in the middle) is an array of (start, end, new) in characters, each on the text that the one before
    it left; ends beyond the text are its end, and null edits change nothing.  A null text is empty,
    with 0 tokens before its edits.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec()
        for batch in batches:
            _, offsets = strings(batch.column(1))
            for at, to in slabs(offsets, SLAB_BYTES):
                texts = [t or "" for t in batch.column(1).slice(at, to - at).to_pylist()]
                trees = [TokenTree(t, own, s) for t, s in zip(texts, measured(texts, own))]
                before = [t.total for t in trees]
                asked = [[e for e in row or [] if e and None not in e.values()] for row in batch.column(2).slice(at, to - at).to_pylist()]
                for k in range(max(map(len, asked), default=0)):
                    now = [(t, e[k]) for t, e in zip(trees, asked) if k < len(e)]
                    regions = [t.region(min(e["start"], t.chars[1]), min(max(e["start"], e["end"]), t.chars[1]), e["new"]) for t, e in now]
                    for (t, _), region, segments in zip(now, regions, measured([r[-1] for r in regions], own)):
                        t.put(region, segments)
                columns = (before, [t.total for t in trees], [t.reencoded for t in trees])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, to - at), *(pa.array(c, pa.int64()) for c in columns)], ["doc_id", "n_tokens", "n_tokens_edited", "reencoded"])

    edits = middle(docs["text"]) if edits is None else edits
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), edits.alias("edits")).mapInArrow(lean(run), "doc_id long, n_tokens long, n_tokens_edited long, reencoded long")


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token counts of every whole text, before and after an edit that the trees follow."""
    return counted(table(spark, sf_dir, "documents"))
