"""Language-model scores by masked pseudo-likelihood.

Every word of the corpus is counted.  The words are dealt to CLASSES by falling count, so that the
classes weigh alike and a frequent word is a class of its own; the last class holds the words that
occur once, of which only the number is kept, as they are alike.  A small network reads the
classes of the two words on either side of a position and predicts the class of the word there, in
two steps: first which of BRANCHES groups of neighbouring classes, then which class of the group.
Times the word's share of its class that is a probability of the word itself.

The vocabulary is a table that grows with the corpus and stays distributed.  A word's class follows
from its count and its fingerprint, so the driver and the workers hold the words of single classes,
the FREQUENT most frequent words and one row for each count that occurs (at most the root of twice
the corpus' words); the counts of all other words reach the texts by a join.

The network is shared: the texts are dealt by hash to shards of about SHARD_BYTES, and in each of
ROUNDS a part of the shards trains it by gradient steps of up to STEP words, every shard from the network
of the round before and in the order of its doc_ids, and Spark averages the shards, weighted by
their words.  Each word trains it once.  So the scores follow from the rows alone, not from batches
or partitions.  A document's score is the sum over all its words of the log-probability given both
sides.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, reliable, table, typed
from .grams import each_slab

CLASSES, BRANCHES, WIDTH, SIDES = 256, 16, 16, (-2, -1, 1, 2)
#: Words of a step at first and at most (a shard's steps double in size), rate, and the past gradients a weight begins with.
FIRST, STEP, RATE, PAST = 64, 1024, 0.1, 1e-6
ROUNDS, SHARD_BYTES, FREQUENT = 4, 2 << 20, 1 << 16
#: Words that are read at once, and that are scored at once.
PIECE, BLOCK = 1 << 17, 4096
_EACH = CLASSES // BRANCHES
_SHAPES = ((len(SIDES), CLASSES + 1, WIDTH), (BRANCHES, WIDTH), (BRANCHES,), (BRANCHES, _EACH, WIDTH), (BRANCHES, _EACH))
_ENDS = np.cumsum([int(np.prod(x)) for x in _SHAPES])
_SIZE = int(_ENDS[-1])


class Deal(NamedTuple):
    """Which class a word is in, from its count and fingerprint, and the log mass of the classes."""

    heads: np.ndarray  # fingerprints (rising) of the words that are a class of their own
    head_kind: np.ndarray
    counts: np.ndarray  # the counts (rising) of the other words seen more than once
    start: np.ndarray  # the mass of the words of higher counts
    width: np.ndarray  # the mass of the words of this count
    first: int  # the first class of several words
    once: int  # words seen once
    mass: np.ndarray

    def kind(self, words: np.ndarray, n: np.ndarray) -> np.ndarray:
        """The class of words seen n times; words of one count are dealt by fingerprint."""
        out = np.full(len(words), CLASSES - 1, dtype=np.int16)
        several = np.flatnonzero(n > 1)
        if len(self.counts) and len(several):
            i = np.minimum(np.searchsorted(self.counts, n[several]), len(self.counts) - 1)
            place = self.start[i] + self.width[i] * ((words[several] >> np.uint64(11)) / 2.0**53)
            total = self.start[0] + self.width[0]
            out[several] = np.minimum(self.first + (place * ((CLASSES - 1 - self.first) / total)).astype(np.int64), CLASSES - 2)
        if len(self.heads):
            i = np.minimum(np.searchsorted(self.heads, words), len(self.heads) - 1)
            own = self.heads[i] == words
            out[own] = self.head_kind[i[own]]
        return out

    def share(self, kind: np.ndarray, n: np.ndarray) -> np.ndarray:
        """The log share of words in their classes; that of a word seen once or never is 1 / (words seen once + 1)."""
        return np.where(n > 1, np.log(np.maximum(n, 1)) - self.mass[kind], -np.log(self.once + 1.0))


class Counted:
    """The words seen more than once and how often, (w, n), as a table of known length."""

    def __init__(self, rows: DataFrame, length: int):
        self.rows, self.length = rows, length

    def __len__(self) -> int:
        return self.length


class Vocabulary(NamedTuple):
    """All words seen more than once; the classes; fingerprints (rising) and counts of the frequent words."""

    words: Counted
    deal: Deal
    frequent: tuple[np.ndarray, np.ndarray]


class Model(NamedTuple):
    vocabulary: Vocabulary
    flat: np.ndarray


def start(deal: Deal | None = None) -> np.ndarray:
    """The network before training; a class without words has no share of the probability, then and later."""
    own = np.random.default_rng(7).normal(scale=0.3, size=_SIZE).astype(np.float32)
    _, _, first, _, second = _parts(own)
    first[:], second[:] = 0, 0
    if deal is not None:
        closed = (deal.mass < 0).reshape(BRANCHES, _EACH)
        closed[-1, -1] = False  # words never seen are in the last class
        second[closed], first[closed.all(axis=1)] = -1e4, -1e4
    return own


def _parts(flat: np.ndarray) -> list[np.ndarray]:
    """Views: the inputs of each side, the groups' weights and biases, the classes' weights and biases by group."""
    return [flat[z - int(np.prod(x)) : z].reshape(x) for x, z in zip(_SHAPES, _ENDS.tolist())]


def dealt(frequent: tuple[np.ndarray, np.ndarray], histogram: dict[int, int], once: int) -> Deal:
    """The classes of the words of a ``histogram`` (words by count above 1); ``frequent`` are those of its highest counts."""
    words, n = frequent
    order = np.lexsort((words, -n))
    words, n, rest = words[order], n[order], dict(histogram)
    left, i = sum(c * m for c, m in histogram.items()), 0
    while i < min(len(words), CLASSES - 2) and int(n[i]) * (CLASSES - 1 - i) >= left:
        left, i = left - int(n[i]), i + 1
        rest[int(n[i - 1])] -= 1
    counts = np.array(sorted(c for c, m in rest.items() if m), dtype=np.int64)
    width = np.array([float(c) * rest[c] for c in counts.tolist()])
    rising = np.argsort(words[:i])
    return Deal(words[:i][rising], rising.astype(np.int16), counts, np.cumsum(width[::-1])[::-1] - width, width, i, once, np.zeros(CLASSES))


def vocabulary(docs: DataFrame) -> Vocabulary:
    """All words of the corpus by count."""
    context = docs.sparkSession.sparkContext

    def count(batches):
        for batch in batches:
            own = [words for _, _, words, _ in each_slab(batch.column(0), lower=True)]
            words, n = np.unique(np.concatenate([np.zeros(0, np.uint64), *own]), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(words.view(np.int64)), pa.array(n.astype(np.int64))], ["w", "n"])

    def fold(batches):
        once = 0
        for batch in batches:
            several = batch.column(1).to_numpy() > 1
            once += int((~several).sum())
            yield batch.filter(pa.array(several))
        yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([once], pa.int64())], ["w", "n"])

    sent = docs.select(F.col("text").cast("string")).mapInArrow(lean(count), "w long, n long")
    got = reliable(sent.groupBy("w").agg(F.sum("n").alias("n")).mapInArrow(lean(fold), "w long, n long"))
    words = got.where("w IS NOT NULL")
    once = got.where("w IS NULL").agg(F.sum("n")).first()[0] or 0
    histogram = {r.n: r.m for r in words.groupBy("n").agg(F.count(F.lit(1)).alias("m")).collect()}
    least, held = 1 << 62, 0
    for n in sorted(histogram, reverse=True):
        held += histogram[n]
        if held > FREQUENT:
            break
        least = n
    top = words.where(F.col("n") >= least).toArrow()
    frequent = top.column("w").to_numpy().view(np.uint64), top.column("n").to_numpy().astype(np.int64)
    order = np.argsort(frequent[0])
    frequent = frequent[0][order], frequent[1][order]
    deal = dealt(frequent, histogram, once)
    sent_deal = context.broadcast(deal)

    def weigh(batches):
        mass = np.zeros(CLASSES)
        for batch in batches:
            n = batch.column(1).to_numpy()
            mass += np.bincount(sent_deal.value.kind(batch.column(0).to_numpy().view(np.uint64), n), n, CLASSES)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(CLASSES, dtype=np.int32)), pa.array(mass)], ["kind", "mass"])

    mass = np.full(CLASSES, 0.5)  # of a class without words: its log is below 0
    for r in words.mapInArrow(lean(weigh), "kind int, mass double").groupBy("kind").agg(F.sum("mass").alias("mass")).collect():
        mass[r.kind] = r.mass or 0.5
    return Vocabulary(Counted(words, sum(histogram.values())), deal._replace(mass=np.log(mass)), frequent)


class _Finder:
    """Counts of words: a table of one place a word for most, a search for the others."""

    def __init__(self, words: np.ndarray, n: np.ndarray):
        self.words, self.n = words, n
        self.shift = np.uint64(64 - max(4, int(len(words)).bit_length() + 3))
        self.table = np.full(1 << (64 - int(self.shift)), -1, dtype=np.int32)
        self.table[(words >> self.shift).astype(np.int64)] = np.arange(len(words))

    def __call__(self, words: np.ndarray) -> np.ndarray:
        """Where each of ``words`` stands, or -1."""
        at = self.table[(words >> self.shift).astype(np.int64)]
        if not len(self.words):
            return at
        again = np.flatnonzero((at >= 0) & (self.words[at] != words))
        i = np.minimum(np.searchsorted(self.words, words[again]), len(self.words) - 1)
        at[again] = np.where(self.words[i] == words[again], i, -1)
        return at


def encoded(docs: DataFrame, known: Vocabulary) -> DataFrame:
    """shard, doc_id, n_words, kinds (the classes of the words, two bytes each) and share (summed log shares) of every row.

    A shard's rows are together and in the order of doc_id (null first) and text.  Null and empty
    texts have no words; equal rows stand beside each other.  Written to the checkpoint folder.
    """
    context = docs.sparkSession.sparkContext
    named = docs if "doc_id" in docs.columns else docs.withColumn("doc_id", F.lit(None).cast("bigint"))
    own = typed(named, doc_id="bigint", text="string")
    size = own.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    shards = ROUNDS * max(1, -(-size // (ROUNDS * SHARD_BYTES)))
    own = own.withColumn("key", F.xxhash64("doc_id", "text")).withColumn("shard", F.pmod(F.col("key"), F.lit(shards)))
    shared = context.broadcast((known.frequent, known.deal))

    def wanted(batches):
        finder = _Finder(*shared.value[0])
        for batch in batches:
            shard = batch.column(0).to_numpy()
            for at, to, words, bounds in each_slab(batch.column(1), lower=True):
                s = np.repeat(shard[at:to], np.diff(bounds))
                rare = finder(words) < 0
                s, w = s[rare], words[rare]
                order = np.lexsort((w, s))
                s, w = s[order], w[order]
                new = np.ones(len(w), dtype=bool)
                new[1:] = (s[1:] != s[:-1]) | (w[1:] != w[:-1])
                yield pa.RecordBatch.from_arrays([pa.array(s[new]), pa.array(w[new].view(np.int64))], ["shard", "w"])

    asked = own.select("shard", "text").mapInArrow(lean(wanted), "shard long, w long")
    found = asked.join(known.words.rows.where(F.col("n") < int(known.frequent[1].min(initial=1 << 62))), "w").select("shard", "w", "n")
    names = ["shard", "doc_id", "n_words", "kinds", "share"]

    def encode(left: pa.Table, right: pa.Table) -> pa.Table:
        (top, top_n), deal = shared.value
        w, first = np.unique(right.column("w").to_numpy().view(np.uint64), return_index=True)
        words, n = np.concatenate([top, w]), np.concatenate([top_n, right.column("n").to_numpy()[first]])
        order = np.argsort(words)
        words, n = words[order], n[order]
        finder, kind = _Finder(words, n), np.append(deal.kind(words, n), np.int16(CLASSES - 1))
        share = np.append(deal.share(kind[:-1], n), -np.log(deal.once + 1.0))
        left = left.sort_by([("doc_id", "ascending"), ("key", "ascending")]) if left.num_rows else left
        kinds, shares, counts = [], [], []
        for _, _, seen, bounds in each_slab(left.column("text"), lower=True):
            at = finder(seen)
            raw, sums = kind[at].astype("<i2").tobytes(), np.append(0.0, np.cumsum(share[at]))[bounds]
            kinds += [raw[2 * x : 2 * y] for x, y in zip(bounds[:-1].tolist(), bounds[1:].tolist())]
            shares.append(np.diff(sums))
            counts.append(np.diff(bounds))
        none = [np.zeros(0, np.int64)]
        columns = [left.column("shard"), left.column("doc_id"), pa.array(np.concatenate(none + counts)), pa.array(kinds, pa.binary()), pa.array(np.concatenate([np.zeros(0), *shares]))]
        return pa.Table.from_arrays(columns, names)

    rows = own.groupBy("shard").cogroup(found.groupBy("shard")).applyInArrow(encode, "shard long, doc_id long, n_words long, kinds binary, share double")
    return reliable(rows)


def _positions(kinds: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Row, class and neighbours' classes (CLASSES beyond the ends of a text) of every word, some whole rows at a time."""
    size = np.array([0, *np.cumsum([len(x.as_buffer()) if x.is_valid else 0 for x in kinds])], dtype=np.int64) // 2
    at = 0
    while at < len(kinds):
        to = max(at + 1, int(np.searchsorted(size, size[at] + PIECE, side="right")) - 1)
        kind = np.frombuffer(b"".join(x.as_buffer() for x in kinds.slice(at, to - at) if x.is_valid), dtype="<i2").astype(np.int64)
        bounds = size[at : to + 1] - size[at]
        row = np.repeat(np.arange(to - at), np.diff(bounds))
        place, around = np.arange(len(kind)), np.full((len(SIDES), len(kind)), CLASSES)
        for i, d in enumerate(SIDES):
            j = place + d
            ok = (j >= bounds[row]) & (j < bounds[row + 1])
            around[i, ok] = kind[j[ok]]
        yield at + row, kind, around
        at = to


def _softmax(z: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The log-probability of ``at`` in each column; ``z`` becomes the probabilities."""
    z -= z.max(axis=0)
    own = z[at, np.arange(z.shape[1])]
    np.exp(z, out=z)
    total = z.sum(axis=0)
    z /= total
    return own - np.log(total)


def _forward(flat: np.ndarray, kind: np.ndarray, around: np.ndarray) -> tuple:
    """Hidden layer, group probabilities, order of the words by group, the groups' ends, class probabilities in that order, and log-probabilities."""
    inputs, top, first, out, second = _parts(flat)
    hidden = np.take(inputs[0], around[0], axis=0)
    for i in range(1, len(SIDES)):
        hidden += np.take(inputs[i], around[i], axis=0)
    hidden /= 1 + np.abs(hidden)
    group = (kind // _EACH).astype(np.int8)
    p = top @ hidden.T + first[:, None]
    logp = _softmax(p, group)
    order = np.argsort(group, kind="stable")
    ends = np.cumsum(np.bincount(group, minlength=BRANCHES)).tolist()
    sorted_hidden, q = hidden[order], np.empty((_EACH, len(kind)), dtype=flat.dtype)
    for g, (x, y) in enumerate(zip([0, *ends], ends)):
        if y > x:
            q[:, x:y] = out[g] @ sorted_hidden[x:y].T + second[g][:, None]
    logp[order] += _softmax(q, (kind % _EACH)[order])
    return hidden, p, order, ends, sorted_hidden, q, logp


class Trainer:
    """A copy of the network that takes gradient steps word by word in order, however the words arrive.

    Steps begin with FIRST words and grow to STEP; each weight's rate falls with its past gradients.
    """

    def __init__(self, flat: np.ndarray):
        self.flat, self.past, self.slope = flat.copy(), np.full(_SIZE, PAST, dtype=np.float32), np.empty(_SIZE, dtype=np.float32)
        self.words, self.steps = 0, 0
        self.held: tuple[np.ndarray, np.ndarray] = np.zeros(0, np.int64), np.zeros((len(SIDES), 0), np.int64)

    def take(self, kind: np.ndarray, around: np.ndarray) -> None:
        kind, around = np.concatenate([self.held[0], kind]), np.concatenate([self.held[1], around], axis=1)
        s = 0
        while s + (size := min(STEP, FIRST << (self.steps // 4))) <= len(kind):
            self.step(kind[s : s + size], around[:, s : s + size])
            s += size
        self.held = kind[s:], around[:, s:]

    def end(self) -> np.ndarray:
        if len(self.held[0]):
            self.step(*self.held)
        return self.flat

    def step(self, kind: np.ndarray, around: np.ndarray) -> None:
        n, every = len(kind), np.arange(len(kind))
        _, top, _, out, _ = _parts(self.flat)
        d_inputs, d_top, d_first, d_out, d_second = _parts(self.slope)
        hidden, p, order, ends, sorted_hidden, q, _ = _forward(self.flat, kind, around)
        p[kind // _EACH, every] -= 1
        q[(kind % _EACH)[order], every] -= 1
        p /= n
        q /= n
        np.matmul(p, hidden, out=d_top)
        p.sum(axis=1, out=d_first)
        back, sorted_back = p.T @ top, np.empty_like(sorted_hidden)
        for g, (x, y) in enumerate(zip([0, *ends], ends)):
            own = q[:, x:y]
            np.matmul(own, sorted_hidden[x:y], out=d_out[g])
            own.sum(axis=1, out=d_second[g])
            sorted_back[x:y] = own.T @ out[g]
        back[order] += sorted_back
        back *= (1 - np.abs(hidden)) ** 2
        cells, flat_back = np.arange(WIDTH), back.ravel()
        for i in range(len(SIDES)):
            d_inputs[i] = np.bincount((around[i][:, None] * WIDTH + cells).ravel(), flat_back, (CLASSES + 1) * WIDTH).reshape(CLASSES + 1, WIDTH)
        self.past += self.slope**2
        self.flat -= RATE * self.slope / np.sqrt(self.past)
        self.words, self.steps = self.words + n, self.steps + 1


def trained(corpus: DataFrame, deal: Deal) -> np.ndarray:
    """The network of an encoded corpus; one of no words gives the starting network."""
    context, flat = corpus.sparkSession.sparkContext, start(deal)
    for r in range(ROUNDS):
        shared = context.broadcast(flat)

        def run(batches, shared=shared):
            total, n, now, own = np.zeros(_SIZE), 0, None, None
            for batch in batches:
                shard = batch.column(0).to_numpy()
                cuts = np.append(np.flatnonzero(np.diff(shard, prepend=shard[:1] - 1)), len(shard)) if len(shard) else np.zeros(1, np.int64)
                for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
                    if shard[x] != now:
                        if own is not None:
                            total, n = total + own.end() * float(own.words), n + own.words
                        now, own = shard[x], Trainer(shared.value)
                    for _, kind, around in _positions(batch.column(1).slice(x, y - x)):
                        own.take(kind, around)
            if own is not None:
                last = own.end()
                total, n = total + last * float(own.words), n + own.words
            if n:
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(_SIZE, dtype=np.int32)), pa.array(total), pa.array(np.full(_SIZE, n, dtype=np.int64))], ["i", "v", "n"])

        rows = corpus.where(F.pmod(F.col("shard"), F.lit(ROUNDS)) == r).select("shard", "kinds").mapInArrow(lean(run), "i int, v double, n long")
        got = rows.groupBy("i").agg((F.sum("v") / F.sum("n")).alias("v")).orderBy("i").collect()
        if got:
            flat = np.array([x.v for x in got], dtype=np.float32)
    return flat


def fit(docs: DataFrame) -> Model:
    """The vocabulary and the network of the whole corpus; an empty one gives the starting network.

    Only text and, if there, doc_id are read.  Null and empty texts teach nothing; repeated rows count each for
    itself; texts of any length are read whole.
    """
    known = vocabulary(docs)
    return Model(known, trained(encoded(docs, known), known.deal))


def _scored(rows: DataFrame, flat: np.ndarray) -> DataFrame:
    # in doubles and rounded, so that a text's score does not depend on where it stands in a block
    sent = rows.sparkSession.sparkContext.broadcast(flat.astype(np.float64))

    def run(batches):
        for batch in batches:
            count, total = batch.column(1).to_numpy(), batch.column(3).to_numpy().copy()
            for row, kind, around in _positions(batch.column(2)):
                logp = [_forward(sent.value, kind[s : s + BLOCK], around[:, s : s + BLOCK])[-1] for s in range(0, len(kind), BLOCK)]
                total += np.bincount(row, np.concatenate([np.zeros(0), *logp]), batch.num_rows)
            total = np.round(total, 6)
            mean = pa.array(total / np.maximum(count, 1), mask=count == 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(total), mean], ["doc_id", "n_words", "log_likelihood", "mean"])

    return rows.select("doc_id", "n_words", "kinds", "share").mapInArrow(lean(run), "doc_id long, n_words long, log_likelihood double, mean double")


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, n_words, log_likelihood (summed) and mean; a text of no words has 0 and a null mean.

    A null doc_id stays null; equal texts score alike and repeated rows give repeated results; texts
    of any length are scored whole; words that the corpus does not have count as words seen once; an
    empty table gives an empty result; columns other than doc_id and text are not read.
    """
    return _scored(encoded(docs, model.vocabulary), model.flat)


def op5_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every whole text scored by a network of the whole corpus; the texts are encoded once for both."""
    docs = table(spark, sf_dir, "documents")
    known = vocabulary(docs)
    rows = encoded(docs, known)
    return _scored(rows, trained(rows, known.deal))
