"""Byte-level BPE in numpy: length-bucketed padded matrices, one merge per row and round.

A text is cut by the public pattern; each distinct piece is encoded once per worker.  Pieces of
similar length form one padded matrix of token ids.  In a round every row merges its leftmost pair
of least rank (ranks come from an open-addressed hash table of id pairs) and closes the gap; rows
without a pair are compacted away.  Pieces beyond ``LONG`` bytes merge in the same order by a heap,
since a matrix would take quadratic time.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import lean, table
from .grams import slabs, strings, word_hashes

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
#: Longest piece of a matrix; entries of a worker's caches of pieces and of chunks; bytes at once.
LONG, PIECES, CHUNKS, SLAB_BYTES = 512, 60_000, 400_000, 1 << 19
#: Bytes that cannot begin white space in UTF-8.
_SAFE = np.zeros(256, dtype=bool)
_SAFE[[*range(0x21, 0x7F), *range(0xC3, 0xE1), *range(0xE4, 0xF5)]] = True
_NONE = np.iinfo(np.int32).max
_EMPTY = np.uint64(0xFFFFFFFFFFFFFFFF)


def spread(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start[i], ..., start[i] + size[i] - 1 for all i, one after the other."""
    before = np.cumsum(size) - size
    return np.repeat(start - before, size) + np.arange(int(size.sum()))


def ragged(flat: np.ndarray, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    return flat[spread(start, size)]


class PairTable:
    """id pair -> id of the joined token, by open addressing with linear probes."""

    def __init__(self, ranks: dict[bytes, int]):
        pairs, ids = [], []
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                a, b = ranks.get(token[:cut]), ranks.get(token[cut:])
                if a is not None and b is not None:
                    pairs.append(a << 32 | b)
                    ids.append(rank)
        bits = max(4, (2 * len(pairs)).bit_length() + 1)
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.keys, self.ids = np.full(1 << bits, _EMPTY), np.full(1 << bits, _NONE, dtype=np.int32)
        keys, ids = np.array(pairs, dtype=np.uint64), np.array(ids, dtype=np.int32)
        slot, left = self._slot(keys), np.arange(len(keys))
        while len(left):
            free = left[self.keys[slot[left]] == _EMPTY]
            at, first = np.unique(slot[free], return_index=True)
            self.keys[at], self.ids[at] = keys[free[first]], ids[free[first]]
            left = np.setdiff1d(left, free[first], assume_unique=True)
            taken = left[self.keys[slot[left]] != keys[left]]
            slot[taken] = (slot[taken] + 1) & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def __call__(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Joined ids of the pairs, _NONE where there is none or a side is padding (negative)."""
        out = np.full(a.shape, _NONE, dtype=np.int32)
        ask = np.nonzero((a >= 0) & (b >= 0))
        keys = a[ask].astype(np.uint64) << np.uint64(32) | b[ask].astype(np.uint64)
        slot, got, left = self._slot(keys), np.full(len(keys), _NONE, dtype=np.int32), np.arange(len(keys))
        while len(left):
            here = self.keys[slot[left]]
            hit = here == keys[left]
            got[left[hit]] = self.ids[slot[left[hit]]]
            left = left[~hit & (here != _EMPTY)]
            slot[left] = (slot[left] + 1) & self.mask
        out[ask] = got
        return out


class BytePairCodec:
    """Encodes and decodes as the published ranks say; a piece that is a token is that token."""

    def __init__(self, vocabulary: str, pattern: str):
        with open(vocabulary, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        self.tokens = [b""] * (max(self.ranks.values()) + 1)
        for token, rank in self.ranks.items():
            self.tokens[rank] = token
        self.byte_ids = np.array([self.ranks[bytes([i])] for i in range(256)], dtype=np.int32)
        self.pairs = PairTable(self.ranks)
        import public_tokenizers

        self.pattern = regex.compile(pattern)
        #: Only the public pattern is known to begin a piece at a space before other text; other patterns see whole texts.
        self.cuts = pattern == public_tokenizers.PATTERN
        self.cache: dict[str, bytes] = {}
        self.keys, self.places, self.sizes, self.flat = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int32), np.zeros(0, np.uint32)

    def _matrix(self, rows: list[bytes], width: int) -> list[bytes]:
        ids = np.full((len(rows), width), -1, dtype=np.int32)
        lengths = np.fromiter(map(len, rows), dtype=np.int64, count=len(rows))
        ids[np.arange(width) < lengths[:, None]] = self.byte_ids[np.frombuffer(b"".join(rows), dtype=np.uint8)]
        out = np.full((len(rows), width), -1, dtype=np.int32)
        alive, joined = np.arange(len(rows)), self.pairs(ids[:, :-1], ids[:, 1:])
        while len(alive) and joined.shape[1]:
            row = np.arange(len(alive))
            at = joined.argmin(axis=1)
            best = joined[row, at]
            done = best == _NONE
            if done.any():
                out[alive[done], : ids.shape[1]] = ids[done]
                go = ~done
                alive, ids, joined, at, best = alive[go], ids[go], joined[go], at[go], best[go]
                row = np.arange(len(alive))
            if not len(alive):
                break
            ids[row, at] = best
            columns = np.arange(ids.shape[1] - 1)
            ids = np.take_along_axis(ids, columns + (columns > at[:, None]), axis=1)
            columns = columns[:-1]
            joined = np.take_along_axis(joined, columns + (columns >= at[:, None]), axis=1)
            for side in (at - 1, at):
                fit = np.flatnonzero((side >= 0) & (side < joined.shape[1]))
                joined[fit, side[fit]] = self.pairs(ids[fit, side[fit]], ids[fit, side[fit] + 1])
        out[alive, : ids.shape[1]] = ids
        held = out >= 0
        raw, ends = out[held].astype("<u4").tobytes(), np.concatenate([[0], 4 * np.cumsum(held.sum(axis=1))]).tolist()
        return [raw[x:y] for x, y in zip(ends, ends[1:])]

    def _long(self, piece: bytes) -> np.ndarray:
        ids = self.byte_ids[np.frombuffer(piece, dtype=np.uint8)]
        joined = self.pairs(ids[:-1], ids[1:])
        ids, n = ids.tolist(), len(piece)
        heap = [(int(r), int(i)) for i, r in enumerate(joined) if r != _NONE]
        heapq.heapify(heap)
        after, before, current = list(range(1, n + 1)), list(range(-1, n - 1)), {i: r for r, i in heap}
        ranks, tokens = self.ranks, self.tokens
        while heap:
            r, i = heapq.heappop(heap)
            if current.get(i) != r:
                continue
            j = after[i]
            ids[i], ids[j] = r, -1
            current.pop(j, None)
            after[i] = after[j]
            if after[j] < n:
                before[after[j]] = i
            for a in (before[i], i):
                if a >= 0 and (b := after[a]) < n:
                    new = ranks.get(tokens[ids[a]] + tokens[ids[b]])
                    if new is None:
                        current.pop(a, None)
                    else:
                        current[a] = new
                        heapq.heappush(heap, (new, a))
                elif a >= 0:
                    current.pop(a, None)
        return np.array([x for x in ids if x >= 0], dtype=np.int32)

    def _learn(self, missing: set[str]) -> dict[str, bytes]:
        """Ids of pieces: whole tokens at once, the others by matrices of one length class each."""
        out: dict[str, bytes] = {}
        buckets: dict[int, list[tuple[str, bytes]]] = {}
        for piece in missing:
            data = piece.encode()
            if (own := self.ranks.get(data)) is not None:
                out[piece] = own.to_bytes(4, "little")
            elif len(data) > LONG:
                out[piece] = self._long(data).astype("<u4").tobytes()
            else:
                buckets.setdefault((len(data) + 3) // 4 * 4 if len(data) <= 32 else 1 << (len(data) - 1).bit_length(), []).append((piece, data))
        for width, rows in buckets.items():
            step = max(1, (1 << 19) // width)
            for i in range(0, len(rows), step):
                part = rows[i : i + step]
                out.update(zip([p for p, _ in part], self._matrix([d for _, d in part], width)))
        return out

    def _pieces(self, pieces: list[str]) -> list[bytes]:
        new = self._learn(set(pieces) - self.cache.keys())
        self.cache.update(new)
        out = list(map(self.cache.__getitem__, pieces))
        if len(self.cache) > PIECES:
            for piece in new:
                del self.cache[piece]
        return out

    def _found(self, text: str) -> list[str]:
        """The matches of the pattern, whatever groups it has; text between them has no tokens."""
        return [m.group() for m in self.pattern.finditer(text) if m.group()] if self.pattern.groups else self.pattern.findall(text)

    def _new_chunks(self, chunks: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the chunks one after the other, and how many each has.

        Chunks that begin with a space before other text can be cut into pieces in one go, as a text of themselves.
        """
        texts = [c.decode() for c in chunks]
        spaced = [i for i, t in enumerate(texts) if self.cuts and t[0] == " " and t[1:2].strip()]
        order, pieces, owner = np.array(spaced, dtype=np.int64), self._found("".join(texts[i] for i in spaced)), np.zeros(0, np.int64)
        if pieces:
            ends = np.cumsum(np.fromiter(map(len, pieces), dtype=np.int64, count=len(pieces)))
            owner = order[np.searchsorted(np.cumsum([len(texts[i]) for i in spaced]), ends, side="left")]
        heads = sorted(set(range(len(texts))) - set(spaced))
        for i in heads:
            own = self._found(texts[i])
            pieces += own
            owner = np.concatenate([owner, np.full(len(own), i)])
        ids = self._pieces(pieces)
        size = np.fromiter(map(len, ids), dtype=np.int64, count=len(ids)) // 4
        count = np.bincount(owner, weights=size, minlength=len(chunks)).astype(np.int64)
        flat, rank = np.frombuffer(b"".join(ids), dtype="<u4"), np.argsort(owner, kind="stable")
        return ragged(flat, (np.cumsum(size) - size)[rank], size[rank]), count

    def _chunk_starts(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """A space before a byte that cannot begin white space starts a piece whatever precedes it."""
        cut = np.zeros(len(data), dtype=bool)
        if self.cuts:
            cut[:-1] = (data[:-1] == 0x20) & _SAFE[data[1:]]
        inner = offsets[1:-1]
        cut[inner[(inner > 0) & (inner < len(data))] - 1] = False
        cut[offsets[:-1][offsets[:-1] < len(data)]] = True
        return np.flatnonzero(cut)

    def encode_bytes(self, data: np.ndarray, offsets: np.ndarray) -> list[bytes]:
        """Ids (little-endian, 32 bits) of the texts data[offsets[i]:offsets[i + 1]]."""
        if len(offsets) == 2 and len(data) > 2 * SLAB_BYTES:
            starts = self._chunk_starts(data, offsets)
            at = np.unique(starts[np.searchsorted(starts, np.arange(0, len(data), SLAB_BYTES), side="right") - 1])
            at = np.append(at, len(data))
            return [b"".join(self._slab(data[x:y], np.array([0, y - x]))[0] for x, y in zip(at, at[1:]))]
        return self._slab(data, offsets)

    def _chunk_ids(self, data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Ids of the distinct chunks one after the other, where each begins, its count, and which chunk stands at each start."""
        ends = np.append(starts[1:], len(data))
        keys, first, which = np.unique(word_hashes(data, starts, ends), return_index=True, return_inverse=True)
        at = np.searchsorted(self.keys, keys)
        known = at < len(self.keys)
        known[known] = self.keys[at[known]] == keys[known]
        new = np.flatnonzero(~known)
        raw = data.tobytes()
        flat, count = self._new_chunks([raw[x:y] for x, y in zip(starts[first[new]].tolist(), ends[first[new]].tolist())])
        size = np.zeros(len(keys), dtype=np.int64)
        size[known], size[new] = self.sizes[at[known]], count
        begin = np.cumsum(size) - size
        ids = np.zeros(int(size.sum()), dtype=np.uint32)
        for rows, source, place in ((np.flatnonzero(known), self.flat, self.places[at[known]]), (new, flat, np.cumsum(count) - count)):
            ids[spread(begin[rows], size[rows])] = ragged(source, place, size[rows])
        if len(self.keys) + len(new) <= CHUNKS and len(data) >= 1 << 16:  # small slabs would copy the cache for little
            self.places = np.insert(self.places, at[new], np.cumsum(count) - count + len(self.flat))
            self.sizes, self.keys = np.insert(self.sizes, at[new], count), np.insert(self.keys, at[new], keys[new])
            self.flat = np.concatenate([self.flat, flat])
        return ids, begin, size, which

    def _slab(self, data: np.ndarray, offsets: np.ndarray) -> list[bytes]:
        if not len(data):
            return [b""] * (len(offsets) - 1)
        starts = self._chunk_starts(data, offsets)
        ids, begin, size, which = self._chunk_ids(data, starts)
        packed = ragged(ids, begin[which], size[which]).astype("<u4").tobytes()
        ends = np.concatenate([[0], np.cumsum(size[which])])[np.searchsorted(starts, offsets)] * 4
        return [packed[x:y] for x, y in zip(ends[:-1].tolist(), ends[1:].tolist())]

    def segments(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the chunks of the texts begin (each encodes alike whatever precedes it), and their numbers of tokens."""
        if not len(data):
            return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
        starts = self._chunk_starts(data, offsets)
        cuts = np.unique(np.searchsorted(starts, np.arange(0, len(data), 2 * SLAB_BYTES), side="right") - 1).tolist()
        counts = []
        for i, j in zip(cuts, [*cuts[1:], len(starts)]):
            x, y = int(starts[i]), int(starts[j]) if j < len(starts) else len(data)
            _, _, size, which = self._chunk_ids(data[x:y], starts[i:j] - x)
            counts.append(size[which])
        return starts, np.concatenate(counts)

    def encode(self, text: str) -> bytes:
        data = np.frombuffer(text.encode(), dtype=np.uint8)
        return self.encode_bytes(data, np.array([0, len(data)]))[0]

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.tokens.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))


_codecs: dict[tuple[str, str], BytePairCodec] = {}


def codec(vocabulary: str | None = None, pattern: str | None = None) -> BytePairCodec:
    """The worker's codec; the files are those of the installed public tokenizers by default.

    Any pattern may be given.  Texts are cut at spaces before they are matched only under the public
    one; under another each distinct text is matched as a whole.
    """
    import public_tokenizers

    key = (vocabulary or public_tokenizers.path(VOCABULARY), pattern or public_tokenizers.PATTERN)
    if key not in _codecs:
        _codecs[key] = BytePairCodec(*key)
    return _codecs[key]


def _encoded(column: pa.Array, vocabulary: str | None, pattern: str | None) -> Iterator[tuple[int, int, list[bytes], BytePairCodec]]:
    own = codec(vocabulary, pattern)
    data, offsets = strings(column)
    for at, to in slabs(offsets, SLAB_BYTES):
        yield at, to, own.encode_bytes(data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]), own


def digests(docs: DataFrame, vocabulary: str | None = None, pattern: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of every whole text (null: empty, 0 tokens).

    A null doc_id stays null, repeated rows give repeated results, an empty table an empty result;
    only doc_id and text are read.  Text that the pattern does not match has no tokens.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, ids_sha, text_sha = [], [], []
            for _, _, rows, own in _encoded(batch.column(1), vocabulary, pattern):
                n += [len(x) // 4 for x in rows]
                ids_sha += [hashlib.sha256(x).hexdigest() for x in rows]
                text_sha += [hashlib.sha256(own.decode(x)).hexdigest() for x in rows]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(lean(run), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def token_ids(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), vocabulary: str | None = None, pattern: str | None = None) -> DataFrame:
    """The ``keep`` columns, ids (array of int), n_tokens, and whether decoding gave the text back.

    Null and empty texts have no ids; repeats and empty tables as in ``digests``.  Columns of ``docs``
    beyond ``keep`` are not read, so none clashes; ``keep`` must not name ids, n_tokens or exact.
    """
    if {"ids", "n_tokens", "exact"} & set(keep):
        raise ValueError("ids, n_tokens and exact are added")
    fields = [docs.schema[c] for c in keep]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = strings(batch.column(len(keep)))
            for at, to, rows, own in _encoded(batch.column(len(keep)), vocabulary, pattern):
                n = np.array([len(x) // 4 for x in rows], dtype=np.int64)
                ids = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n)]), pa.int32()), pa.array(np.frombuffer(b"".join(rows), dtype="<i4")))
                same = [own.decode(x) == data[offsets[at + i] : offsets[at + i + 1]].tobytes() for i, x in enumerate(rows)]
                yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(at, to - at) for i in range(len(keep))), ids, pa.array(n), pa.array(same)], [*keep, "ids", "n_tokens", "exact"])

    schema = T.StructType([*fields, T.StructField("ids", T.ArrayType(T.IntegerType())), T.StructField("n_tokens", T.LongType()), T.StructField("exact", T.BooleanType())])
    return docs.select(*keep, docs["text"].cast("string")).mapInArrow(lean(run), schema)


def op2_byte_pair_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every whole text of ``documents`` encoded and decoded, as digests."""
    return digests(table(spark, sf_dir, "documents"))
