"""Toxicity: boosted trees over dense features of whole texts, calibrated by isotonic regression.

Features are densities of two lexicons (a short fixed list, and words and word beginnings that the
training labels single out), how often the second person stands near their hits, capitals,
punctuation and obfuscated spellings.  Labels come only from training rows; scores never see
labels, lang, source or doc_id.  The model is fitted on a bounded, hash-chosen sample of labelled
rows (``SAMPLE`` per class); a lexicon has at most ``UNITS`` units, the best of all that the sample
holds; counts of a sample are made by Spark, features of texts by numpy over Arrow batches.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .boosting import Boosted, Isotonic
from .common import lean, table
from .grams import _power, _BASE, _INVERSE, _VALUES, mix, slabs, strings, word_spans

#: Labelled rows of a class (clean, toxic) that a fit takes at most; folds; most learned units.
SAMPLE, FOLDS, UNITS = (8000, 4000), 4, 2000
#: Bytes of the word beginnings that count as units beside whole words.
STEMS = (4, 5, 6)
# Common insults and the second person in four languages.
INSULTS = """idiot moron stupid loser scum trash clown pathetic worthless disgusting dumb fool jerk bastard
    filth vermin imbecile cretin freak creep crap shit fuck bitch asshole retard whore slut
    idiote imbécile crétin abruti connard salaud ordure pourri débile conne merde
    dumm dummkopf arschloch trottel depp abschaum dreck widerlich wertlos schlampe scheisse
    estúpido imbécil tonto basura asqueroso patético escoria payaso mierda cabrón puta""".split()
SECOND = """you your yours yourself u ur tu te toi ton ta tes vous votre vos du dich dir dein deine ihr euch euer
    sie tú ti tuyo tus usted ustedes vosotros vuestro""".split()
NEAR = 5
_LEET = str.maketrans({"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s", "!": "i", "|": "l", "€": "e"})
_LETTERS_ONLY = re.compile(r"[^a-zà-öø-ÿ]+")
_BYTES = np.arange(256)
_LETTER = ((_BYTES >= 65) & (_BYTES <= 90)) | ((_BYTES >= 97) & (_BYTES <= 122)) | (_BYTES >= 128)
_UPPER = (_BYTES >= 65) & (_BYTES <= 90)
_DIGIT = (_BYTES >= 48) & (_BYTES <= 57)
_SPACE = (_BYTES == 32) | ((_BYTES >= 9) & (_BYTES <= 13))
_MARK = ~_LETTER & ~_DIGIT & ~_SPACE & (_BYTES > 32)
NAMES = (
    "fixed_hits", "fixed_density", "learned_hits", "learned_weight", "learned_density", "stem_hits", "stem_weight", "best_weight", "second_near",
    "second_density", "capitals", "all_caps", "shouts", "punctuation", "obfuscated", "hidden_hits", "log_words",
)


def _hash(total: np.ndarray, inverse: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    return mix((total[ends] - total[starts]) * inverse[starts] + mix((ends - starts).astype(np.uint64)))


class Words:
    """Letter runs of a slab of texts with the fingerprints of the runs and of their beginnings."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        self.data, self.offsets = data, offsets
        self.starts, self.ends, self.bounds = word_spans(data, offsets, ~_LETTER)
        n = len(data)
        self.total = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum(_VALUES[True][data] * _power("base", _BASE, n + 1)[:n], out=self.total[1:])
        self.inverse = _power("inverse", _INVERSE, n + 1)
        self.doc = np.repeat(np.arange(len(offsets) - 1), np.diff(self.bounds))
        self.whole = _hash(self.total, self.inverse, self.starts, self.ends)

    def stems(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Indices of the words longer than ``size`` bytes and the fingerprints of their first bytes."""
        at = np.flatnonzero(self.ends - self.starts > size)
        return at, _hash(self.total, self.inverse, self.starts[at], self.starts[at] + size) ^ np.uint64(size)

    def units(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        yield self.doc, self.whole
        for size in STEMS:
            at, h = self.stems(size)
            yield self.doc[at], h


def fingerprints(words: list[str]) -> np.ndarray:
    raw = [w.encode() for w in words]
    own = Words(np.frombuffer(b" ".join(raw), dtype=np.uint8), np.array([0, sum(map(len, raw)) + len(raw) - 1]))
    return np.unique(own.whole)


_FIXED, _SECOND = fingerprints(INSULTS), fingerprints(SECOND)
_PLAIN = frozenset(INSULTS)
_LONGEST = max(map(len, INSULTS))
_ASCII_LETTER = ((_BYTES >= 65) & (_BYTES <= 90)) | ((_BYTES >= 97) & (_BYTES <= 122))


def _found(keys: np.ndarray, sorted_keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which keys occur in a sorted array, and where."""
    at = np.searchsorted(sorted_keys, keys)
    at[at == len(sorted_keys)] = 0
    return (sorted_keys[at] == keys, at) if len(sorted_keys) else (np.zeros(len(keys), bool), at)


def featured(data: np.ndarray, offsets: np.ndarray, keys: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """One row of NAMES per text; ``keys`` are the learned units in order, with their weights."""
    n, w = len(offsets) - 1, Words(data, offsets)
    add = lambda doc, value=None: np.bincount(doc, value, n)[:n]
    fixed, _ = _found(w.whole, _FIXED)
    learned, at = _found(w.whole, keys)
    hit = fixed | learned
    weight = np.where(learned, weights[at] if len(weights) else 0.0, 0.0)
    best = np.zeros(n)
    np.maximum.at(best, w.doc[learned], weight[learned])
    stem_hits, stem_weight = np.zeros(n), np.zeros(n)
    strongest = np.zeros(len(w.whole))
    for size in STEMS:
        index, h = w.stems(size)
        ok, place = _found(h, keys)
        if ok.any():
            np.maximum.at(strongest, index[ok], weights[place[ok]])
    stem = strongest > 0
    hit |= stem
    stem_hits, stem_weight = add(w.doc[stem]), add(w.doc[stem], strongest[stem])
    np.maximum.at(best, w.doc[stem], strongest[stem])
    second, _ = _found(w.whole, _SECOND)
    near = np.zeros(n)
    if hit.any() and second.any():
        marks = np.flatnonzero(second)
        own = np.flatnonzero(hit)
        for side in (np.searchsorted(marks, own), np.searchsorted(marks, own) - 1):
            fit = (side >= 0) & (side < len(marks))
            close = own[fit][(np.abs(marks[side[fit]] - own[fit]) <= NEAR) & (w.doc[marks[side[fit]]] == w.doc[own[fit]])]
            near += add(w.doc[close])
    byte_doc = np.repeat(np.arange(n), np.diff(offsets))
    letters, upper = add(byte_doc, _LETTER[data].astype(float)), add(byte_doc, _UPPER[data].astype(float))
    upper_at = np.concatenate([[0], np.cumsum(_UPPER[data])])
    caps = (upper_at[w.ends] - upper_at[w.starts] == w.ends - w.starts) & (w.ends - w.starts > 2)
    marks, shouts = add(byte_doc, _MARK[data].astype(float)), add(byte_doc, np.isin(data, (33, 63)).astype(float))
    starts, ends, bounds = word_spans(data, offsets)
    letter_at, odd_at = np.concatenate([[0], np.cumsum(_LETTER[data])]), np.concatenate([[0], np.cumsum(_MARK[data] | _DIGIT[data])])
    inside = (odd_at[np.maximum(ends - 1, starts)] - odd_at[np.minimum(starts + 1, ends)] > 0) & (letter_at[ends] - letter_at[starts] >= 2)
    doc = np.repeat(np.arange(n), np.diff(bounds))
    # a spelling keeps all ASCII letters of its word, so a word with more of them than any insult has hides none
    plain_at = np.concatenate([[0], np.cumsum(_ASCII_LETTER[data])])
    odd = np.flatnonzero(inside & (plain_at[ends] - plain_at[starts] <= _LONGEST))
    hidden, raw = np.zeros(n), data.tobytes()
    for i in odd:
        spelled = _LETTERS_ONLY.sub("", raw[starts[i] : ends[i]].decode("utf-8", "ignore").lower().strip(".,;:!?\"'()").translate(_LEET))
        if spelled in _PLAIN:
            hidden[doc[i]] += 1
    words, size = np.maximum(np.diff(w.bounds), 1), np.maximum(np.diff(offsets), 1)
    fixed_hits, learned_hits = add(w.doc[fixed]), add(w.doc[learned])
    return np.stack([
        fixed_hits, fixed_hits / words, learned_hits, add(w.doc, weight), learned_hits / words, stem_hits, stem_weight, best, near, add(w.doc[second]) / words,
        upper / np.maximum(letters, 1), add(w.doc[caps]) / words, shouts / size, marks / size, add(doc[inside]) / np.maximum(np.diff(bounds), 1), hidden, np.log1p(np.diff(w.bounds)),
    ], axis=1)


def held_out(doc_id: Column) -> Column:
    return (F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 5) == 0


def _fold(doc_id: Column) -> Column:
    return F.pmod(F.xxhash64(F.lit(3), doc_id), F.lit(FOLDS)).cast("int")


def sampled(docs: DataFrame, labels: DataFrame) -> tuple[DataFrame, dict[int, float]]:
    """(doc_id, text, toxic, fold) of the labelled training rows that a fit takes, and the class weights.

    Of each class the rows of least hash, at most SAMPLE of them, so the sample is the same for the
    same labels; weights restore the classes' shares.  A doc_id with several labels takes the highest.
    """
    known = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    picked, weights = [], {}
    totals = {r.toxic: r["count"] for r in known.groupBy("toxic").count().collect()}
    for c in (0, 1):
        picked.append(known.where(F.col("toxic") == c).orderBy(F.xxhash64("doc_id"), "doc_id").limit(SAMPLE[c]))
        weights[c] = max(1.0, totals.get(c, 0) / SAMPLE[c])
    chosen = picked[0].union(picked[1]).select(F.col("doc_id").alias("labelled"), "toxic")
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), F.col("doc_id") == F.col("labelled"))
    return rows.select("doc_id", "text", "toxic", _fold(F.col("doc_id")).alias("fold")), weights


def _unit_counts(rows: DataFrame) -> DataFrame:
    """unit, c{0,1}{fold}: documents of each class and fold that have a unit, by Spark over all units."""

    def run(batches):
        for batch in batches:
            data, offsets = strings(batch.column(0))
            group = FOLDS * np.asarray(batch.column(1)) + np.asarray(batch.column(2))
            for at, to in slabs(offsets):
                w = Words(data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at])
                seen = []
                for doc, h in w.units():
                    order = np.lexsort((doc, h))
                    doc, h = doc[order], h[order]
                    new = np.ones(len(h), dtype=bool)
                    new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
                    seen.append((h[new], group[at + doc[new]]))
                h, g = (np.concatenate(x) for x in zip(*seen))
                for k in np.unique(g).tolist():
                    unit, n = np.unique(h[g == k], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(unit.view(np.int64)), pa.array(np.full(len(unit), k, np.int32)), pa.array(n.astype(np.int64))], ["unit", "g", "n"])

    counts = [F.sum(F.when(F.col("g") == FOLDS * c + k, F.col("n")).otherwise(0)).alias(f"c{c}{k}") for c in (0, 1) for k in range(FOLDS)]
    return rows.select("text", "toxic", "fold").mapInArrow(lean(run), "unit long, g int, n long").groupBy("unit").agg(*counts)


def _lexicons(counts: DataFrame, sizes: dict[tuple[int, int], int]) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each fold (of the others) and for all: the units that toxic documents have far more often than
    chance has it, with their log odds ratio.

    The odds of every unit with three toxic documents or more are found by Spark; the UNITS of the
    best lower bound (ratio less two spreads, ties to the smaller fingerprint) come to the driver.
    """
    chosen = []
    for k in [*range(FOLDS), None]:
        use = [i for i in range(FOLDS) if i != k]
        n0, n1 = (float(sum(sizes.get((c, i), 0) for i in use)) for c in (0, 1))
        clean, toxic = (sum((F.col(f"c{c}{i}") for i in use), F.lit(0)).cast("double") for c in (0, 1))
        a, b = (F.least((x + 0.5) / (n + 1), F.lit(0.999)) for x, n in ((toxic, n1), (clean, n0)))
        ratio, spread = F.log(a / (1 - a)) - F.log(b / (1 - b)), F.sqrt(1 / (toxic + 0.5) + 1 / (clean + 0.5))
        fit = (toxic >= 3) & (ratio > 1.5) & (ratio > 2.5 * spread) & (toxic * n0 > 4 * clean * n1)
        own = counts.where(fit).select(F.lit(-1 if k is None else k).alias("k"), "unit", ratio.alias("ratio"), (ratio - 2 * spread).alias("worth"))
        chosen.append(own.orderBy(F.desc("worth"), "unit").limit(UNITS))
    got = chosen[0]
    for c in chosen[1:]:
        got = got.unionByName(c)
    got, out = got.toPandas(), []
    for k in [*range(FOLDS), -1]:
        own = got[got["k"] == k]
        units = own["unit"].to_numpy().astype(np.int64).view(np.uint64)
        order = np.argsort(units)
        out.append((units[order], own["ratio"].to_numpy(dtype=np.float64)[order]))
    return out


class Model:
    """Learned units, trees and calibration; ``score`` gives the toxicity of texts as bytes and offsets."""

    def __init__(self, keys: np.ndarray, weights: np.ndarray, trees: Boosted | None, calibration: Isotonic | None):
        self.keys, self.weights, self.trees, self.calibration = keys, weights, trees, calibration

    def score(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        x = featured(data, offsets, self.keys, self.weights)
        if self.trees is None:  # no labels of both classes: the fixed lexicon alone
            hits = x[:, 0] + x[:, 15]
            return hits / (hits + 1.5)
        return np.clip(self.calibration(self.trees.margin(x)), 0.0, 1.0)


def fit(docs: DataFrame, labels: DataFrame) -> Model:
    """A model of the training rows; units of a row's own fold are not used for its features while fitting.

    ``docs`` has doc_id and text, ``labels`` doc_id and toxic; other columns are not read.  Null texts
    are empty texts; rows of null doc_id, of no label, or of a label other than 0 and 1 teach nothing;
    a doc_id with several labels counts with the highest, a repeated document once a row.  Whole
    texts are read, however long.  Empty tables, or labels of one class, give the model of the fixed
    lexicon alone.  Columns of any other name may be there, and none is added to ``docs``.
    """
    spark = docs.sparkSession
    rows, class_weight = sampled(docs, labels)
    rows = rows.persist()
    sizes = {(r.toxic, r.fold): r["count"] for r in rows.groupBy("toxic", "fold").count().collect()}
    total = [sum(v for (c, _), v in sizes.items() if c == t) for t in (0, 1)]
    if min(total) < 2:
        rows.unpersist()
        return Model(np.zeros(0, np.uint64), np.zeros(0), None, None)
    counts = _unit_counts(rows).where(" + ".join(f"c1{k}" for k in range(FOLDS)) + " >= 3").persist()
    lexicons = _lexicons(counts, sizes)
    counts.unpersist()
    sent = spark.sparkContext.broadcast(lexicons)

    def run(batches):
        for batch in batches:
            data, offsets = strings(batch.column(0))
            fold, label = np.asarray(batch.column(1)), batch.column(2)
            for at, to in slabs(offsets):
                part, own = data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
                x = np.zeros((to - at, len(NAMES)))
                for k in range(FOLDS):
                    x[fold[at:to] == k] = featured(part, own, *sent.value[k])[fold[at:to] == k]
                yield pa.RecordBatch.from_arrays([batch.column(1).slice(at, to - at), label.slice(at, to - at), *(pa.array(x[:, j]) for j in range(len(NAMES)))], ["fold", "toxic", *NAMES])

    got = rows.select("text", "fold", "toxic").mapInArrow(lean(run), "fold int, toxic int, " + ", ".join(f"{c} double" for c in NAMES)).toPandas()
    rows.unpersist()
    got = got.sort_values([*NAMES, "fold", "toxic"])
    x, y, fold = got[list(NAMES)].to_numpy(), got["toxic"].to_numpy(dtype=np.float64), got["fold"].to_numpy()
    weight = np.where(y == 1, class_weight[1], class_weight[0])
    margin = np.zeros(len(y))
    for k in range(FOLDS):
        inside = fold != k
        margin[~inside] = Boosted().fit(x[inside], y[inside], weight[inside]).margin(x[~inside]) if (~inside).any() and inside.any() else 0.0
    return Model(*lexicons[-1], Boosted().fit(x, y, weight), Isotonic().fit(margin, y, weight))


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score, predicted of every row.

    Null and empty texts score as texts of no words; a null doc_id hashes as an empty one; repeated
    rows give repeated results and equal texts equal scores; an empty table gives an empty result;
    columns other than doc_id and text are not read.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            data, offsets = strings(batch.column(2))
            scores = [sent.value.score(data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]) for at, to in slabs(offsets)]
            score = np.concatenate(scores) if scores else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    own = docs.select(F.col("doc_id").cast("long"), held_out(F.col("doc_id")).alias("held_out"), F.col("text").cast("string"))
    return own.mapInArrow(lean(run), "doc_id long, held_out boolean, score double, predicted int")


def without_toxic(docs: DataFrame, model: Model, threshold: float = 0.5) -> DataFrame:
    """The rows of ``docs`` that score under the threshold, with all their columns, whatever their names.

    Null and empty texts are scored as texts of no words, repeated rows each for itself.
    """
    sent, schema = docs.sparkSession.sparkContext.broadcast(model), docs.schema
    place = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            data, offsets = strings(batch.column(place).cast(pa.string()))
            scores = [sent.value.score(data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]) for at, to in slabs(offsets)]
            yield batch.filter(pa.array(np.concatenate(scores) < threshold if scores else [], pa.bool_()))

    return docs.mapInArrow(lean(run), schema)


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every whole text of ``documents`` scored by a model of its labelled training rows.

    One row for each row of ``documents``, nulls, empty texts and repeats as ``scored`` defines them.
    """
    docs = table(spark, sf_dir, "documents")
    return scored(docs, fit(docs, table(spark, sf_dir, "labels")))
