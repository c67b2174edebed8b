"""Substring dedup by seed and extend over winnowed anchors.

The anchor of a window of ``LENGTH`` words is its ANCHOR-word gram of least fingerprint (leftmost
on ties), so equal windows have equal anchors, and neighbouring windows mostly share theirs.
Seed: documents meet on anchors; an anchor in one document only is dropped.  Extend: around the
anchors left, every run of windows with that anchor goes out once as a row of the anchor, and a
window is repeated if a smaller document has it too; runs next to each other join into maximal
repeats, whose words are removed.

What an Arrow batch already shows is settled there: an anchor or a window goes out once per batch,
with the smallest document of the batch (a window with all its places there), so copies in
thousands of documents cost a row per batch.
A window is known by its anchor (64 bits), the anchor's place in it and 48 more bits.

An anchor that goes out more than HOT times (boilerplate beginnings and the like) is hot: the
windows around it meet by anchor and window, not by anchor, so that its many contexts are dealt to
all tasks.  The texts are dealt by doc_id once, for the anchors and for the marks alike.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import compress

import numpy as np
import pyarrow as pa
from numpy.lib.stride_tricks import sliding_window_view
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, table, typed, unused
from .grams import each_slab, mix, slabs, strings, window_hashes
from .jaccard import grouped

LENGTH, ANCHOR = 13, 5
#: Rows of an anchor beyond which its windows are dealt one by one.
HOT = 20_000
_U = np.uint64
_I = np.int64


def _windows(column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """By slab: row, place in the text, anchor and identity below the anchor of every window."""
    span = LENGTH - ANCHOR + 1
    for at, to, words, bounds in each_slab(column):
        grams = window_hashes(words, ANCHOR)
        if len(grams) < span:
            continue
        place = sliding_window_view(grams, span).argmin(axis=1)
        row = np.repeat(np.arange(to - at), np.diff(bounds))[: len(place)]
        inside = np.flatnonzero(np.arange(len(place)) + LENGTH <= bounds[row + 1])
        place, row = place[inside], row[inside]
        own = (window_hashes(words, LENGTH, 1)[inside] >> _U(16)) | (place.astype(np.uint64) << _U(48))
        yield at + row, inside - bounds[row], grams[inside + place], own


def _blobs(row: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, list[bytes]]:
    """The values of each row (rows in order) as bytes."""
    first = np.flatnonzero(np.diff(row, prepend=-1))
    raw, size = values.tobytes(), values.itemsize
    ends = np.append(first, len(row)) * size
    return row[first], [raw[x:y] for x, y in zip(ends[:-1].tolist(), ends[1:].tolist())]


def _seeds(docs: DataFrame) -> DataFrame:
    """doc_id and the anchors (bytes of 64-bit integers) that other documents have too, in several rows.

    ``hot`` are those of them that go out more than HOT times.
    """
    most = HOT

    def send(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            rows, anchors = [np.zeros(0, _I)], [np.zeros(0, np.uint64)]
            for row, _, anchor, _ in _windows(batch.column(1)):
                new = np.ones(len(row), dtype=bool)
                new[1:] = (anchor[1:] != anchor[:-1]) | (row[1:] != row[:-1])
                rows.append(row[new])
                anchors.append(anchor[new])
            row, anchor = np.concatenate(rows), np.concatenate(anchors)
            order = np.lexsort((ids[row], anchor))
            row, anchor = row[order], anchor[order]
            doc = ids[row]
            first = np.ones(len(row), dtype=bool)
            first[1:] = anchor[1:] != anchor[:-1]
            group = np.cumsum(first) - 1
            begin = np.flatnonzero(first)
            several = (doc[np.append(begin[1:], len(row)) - 1] != doc[begin])[group] if len(row) else first
            yield pa.RecordBatch.from_arrays([pa.array(anchor[first].view(_I)), pa.array(doc[first]), pa.nulls(int(first.sum()), pa.binary())], ["k", "doc_id", "known"])
            doc, anchor = doc[several], anchor[several]
            order = np.argsort(doc, kind="stable")
            doc, blobs = _blobs(doc[order], anchor[order])
            yield pa.RecordBatch.from_arrays([pa.array(doc), pa.array(doc), pa.array(blobs, pa.binary())], ["k", "doc_id", "known"])

    def meet(batches):
        for part in grouped(batches, 1):
            known = part.column("known").combine_chunks()
            settled = known.is_valid()
            yield pa.RecordBatch.from_arrays([part.column("doc_id").combine_chunks().filter(settled), known.filter(settled), pa.nulls(int(np.sum(np.asarray(settled))), pa.binary())], ["doc_id", "anchors", "hot"])
            open_rows = np.flatnonzero(~np.asarray(settled))
            k, doc = part.column("k").to_numpy()[open_rows], part.column("doc_id").to_numpy()[open_rows]
            if len(k):
                begin = np.flatnonzero(np.append(True, k[1:] != k[:-1]))
                end = np.append(begin[1:], len(k))
                several = doc[end - 1] != doc[begin]
                for many in (False, True):
                    keep = np.repeat(several & ((end - begin > most) == many), end - begin)
                    own, anchors = doc[keep], k[keep]
                    order = np.argsort(own, kind="stable")
                    own, blobs = _blobs(own[order], anchors[order])
                    columns = [pa.array(blobs, pa.binary()), pa.nulls(len(blobs), pa.binary())]
                    yield pa.RecordBatch.from_arrays([pa.array(own, pa.int64()), *(columns[::-1] if many else columns)], ["doc_id", "anchors", "hot"])

    sent = docs.where("doc_id IS NOT NULL").mapInArrow(lean(send), "k long, doc_id long, known binary")
    return sent.repartition("k").sortWithinPartitions("k", "doc_id").mapInArrow(lean(meet), "doc_id long, anchors binary, hot binary")


_MARKS = "doc_id long, of long, at int, bits int"


def _extended(docs: DataFrame, seeds: DataFrame) -> DataFrame:
    """doc_id, of, first window of a run and the bits of its repeated windows.

    ``docs`` has doc_id, text and, where a doc_id has several texts, ``of``: which of them it is (else 0).
    """
    names = ["doc_id", "of", "at", "bits"]

    def pack(doc, of, at, bits):
        return [pa.array(doc, pa.int64()), pa.array(of, pa.int64()), pa.array(at.astype(np.int32)), pa.array(bits.astype(np.int32))]

    def send(batches):
        for batch in batches:
            ids, which = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            warm, hot = ([np.unique(np.frombuffer(b"".join(x.as_py()), dtype=np.uint64)) for x in batch.column(c)] for c in (3, 4))
            wanted = [np.union1d(a, b) if len(b) else a for a, b in zip(warm, hot)]
            dealt = np.unique(np.concatenate([np.zeros(0, np.uint64), *hot]))
            got = {c: [np.zeros(0, t)] for c, t in (("row", _I), ("at", _I), ("anchor", np.uint64), ("own", np.uint64))}
            for row, at, anchor, own in _windows(batch.column(2)):
                ok = np.zeros(len(row), dtype=bool)
                begin = np.flatnonzero(np.diff(row, prepend=-1))
                for x, y in zip(begin.tolist(), [*begin[1:].tolist(), len(row)]):
                    w = wanted[row[x]]
                    i = np.searchsorted(w, anchor[x:y])
                    i[i == len(w)] = 0
                    ok[x:y] = w[i] == anchor[x:y] if len(w) else False
                for c, v in (("row", row), ("at", at), ("anchor", anchor), ("own", own)):
                    got[c].append(v[ok])
            row, at, anchor, own = (np.concatenate(got[c]) for c in ("row", "at", "anchor", "own"))
            doc, text = ids[row], which[row]
            # a run: neighbouring windows of a row with one anchor in one place; around a hot anchor each window by itself
            run, alone = np.ones(len(row), dtype=bool), np.isin(anchor, dealt) if len(dealt) else np.zeros(len(row), dtype=bool)
            place = at + (own >> _U(48)).astype(_I)
            run[1:] = alone[1:] | (row[1:] != row[:-1]) | (at[1:] != at[:-1] + 1) | (place[1:] != place[:-1]) | (anchor[1:] != anchor[:-1])
            key = np.where(alone, mix(anchor ^ mix(own)), anchor)
            begin = np.flatnonzero(run)
            of = np.cumsum(run) - 1
            order = np.lexsort((doc, own, anchor))
            a, o, d = anchor[order], own[order], doc[order]
            first = np.ones(len(order), dtype=bool)
            first[1:] = (a[1:] != a[:-1]) | (o[1:] != o[:-1])
            least = d[first][np.cumsum(first) - 1] if len(d) else d
            repeated = np.zeros(len(row), dtype=bool)
            repeated[order] = d > least
            open_ = np.zeros(len(row), dtype=bool)
            # every place of a window in its least document: the judgement is by place
            open_[order] = d == least
            bit = (np.int64(1) << (np.arange(len(row)) - begin[of])) if len(row) else np.zeros(0, _I)
            bits = np.bincount(of, weights=bit * repeated, minlength=len(begin)).astype(_I)
            has = bits > 0
            yield pa.RecordBatch.from_arrays([pa.array(doc[begin[has]], pa.int64()), *pack(doc[begin[has]], text[begin[has]], at[begin[has]], bits[has]), pa.nulls(int(has.sum()), pa.binary())], ["k", *names, "own"])
            sent = np.flatnonzero(np.bincount(of, weights=open_, minlength=len(begin)) > 0) if len(row) else np.zeros(0, _I)
            # the anchor's place falls by one from window to window: its first, then 48 bits a window
            raw = own.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6].tobytes()
            ends, start = np.append(begin, len(row)) * 6, (own[begin] >> _U(48)).astype(np.uint8).tobytes()
            # equal runs of a document go once, the further places (32 bits each) behind the windows, their number as bits
            places: dict[tuple, list[int]] = {}
            for i, b in zip(sent.tolist(), begin[sent].tolist()):
                places.setdefault((doc[b], text[b], key[b], start[i : i + 1] + raw[ends[i] : ends[i + 1]]), []).append(b)
            at_ = np.array([p[0] for p in places.values()], dtype=_I)
            more = np.array([len(p) - 1 for p in places.values()], dtype=_I)
            blobs = [blob + at[p[1:]].astype("<i4").tobytes() if len(p) > 1 else blob for (*_, blob), p in places.items()]
            yield pa.RecordBatch.from_arrays([pa.array(key[at_].view(_I)), *pack(doc[at_], text[at_], at[at_], more), pa.array(blobs, pa.binary())], ["k", *names, "own"])

    def meet(batches):
        for part in grouped(batches, 1):
            blobs = part.column("own").combine_chunks()
            settled = np.asarray(blobs.is_valid()) == False  # noqa: E712
            doc, text, at, bits, k = (part.column(c).to_numpy() for c in (*names, "k"))
            if settled.any():
                yield pa.RecordBatch.from_arrays(pack(doc[settled], text[settled], at[settled], bits[settled]), names)
            rest = np.flatnonzero(~settled)
            if not len(rest):
                continue
            data, further = [blobs[i].as_py() for i in rest.tolist()], {}
            for i in np.flatnonzero(bits[rest]).tolist():
                cut = len(data[i]) - 4 * int(bits[rest[i]])
                data[i], further[i] = data[i][:cut], np.frombuffer(data[i][cut:], dtype="<i4")
            count = np.fromiter(map(len, data), dtype=_I, count=len(data)) // 6
            of = np.repeat(np.arange(len(rest)), count)
            nth = np.arange(len(of)) - (np.cumsum(count) - count)[of]
            flat = np.zeros((len(of), 8), dtype=np.uint8)
            flat[:, :6] = np.frombuffer(b"".join(x[1:] for x in data), dtype=np.uint8).reshape(-1, 6)
            flat[:, 6] = np.fromiter((x[0] for x in data), dtype=_I, count=len(data))[of] - nth
            own, bit = flat.reshape(-1).view("<u8"), np.int64(1) << nth
            d, a = doc[rest][of], k[rest][of]
            order = np.lexsort((d, own, a))
            d_, o_, a_ = d[order], own[order], a[order]
            first = np.ones(len(order), dtype=bool)
            first[1:] = (a_[1:] != a_[:-1]) | (o_[1:] != o_[:-1])
            repeated = np.zeros(len(order), dtype=bool)
            repeated[order] = d_ > d_[first][np.cumsum(first) - 1]
            bits = np.bincount(of, weights=bit * repeated, minlength=len(rest)).astype(_I)
            has = bits > 0
            yield pa.RecordBatch.from_arrays(pack(doc[rest][has], text[rest][has], at[rest][has], bits[has]), names)
            again = [i for i in further if has[i]]
            if again:
                n = [len(further[i]) for i in again]
                yield pa.RecordBatch.from_arrays(pack(np.repeat(doc[rest][again], n), np.repeat(text[rest][again], n), np.concatenate([further[i] for i in again]), np.repeat(bits[again], n)), names)

    lists = seeds.groupBy("doc_id").agg(F.collect_list("anchors").alias("anchors"), F.collect_list("hot").alias("hot"))
    which = F.col("of") if "of" in docs.columns else F.lit(0).cast("long").alias("of")
    rows = docs.join(lists, "doc_id").select("doc_id", which, "text", "anchors", "hot")
    sent = rows.mapInArrow(lean(send), f"k long, {_MARKS}, own binary")
    return sent.repartition("k").sortWithinPartitions("k", "doc_id", "of", "at").mapInArrow(lean(meet), _MARKS)


def _covered(n: int, marks: list[dict]) -> np.ndarray:
    """Which of n words lie in a repeated window: the union of the maximal repeats."""
    edge = np.zeros(n + 1, dtype=_I)
    at, bits = (np.array([m[c] for m in marks], dtype=_I) for c in ("at", "bits"))
    for j in range(LENGTH - ANCHOR + 1):
        start = np.unique(at[(bits >> j) & 1 == 1] + j)
        start = start[start + LENGTH <= n]
        np.add.at(edge, start, 1)
        np.add.at(edge, start + LENGTH, -1)
    return np.cumsum(edge[:n]) > 0


def marked(docs: DataFrame, name: str = "marks") -> DataFrame:
    """``docs`` with a column ``name``: the runs of repeated windows of the row's text (null: none).

    Null and empty texts have no words; a null doc_id neither removes nor loses anything; equal
    texts under one doc_id are one document, and different ones of it are judged each for itself
    against the smaller doc_ids; an empty table stays empty.  ``name`` must not be a column of
    ``docs``; any other column may be there.
    """
    if unused(name, docs.columns) != name:
        raise ValueError(f"column {name} exists already")
    id_, of_ = (unused(x, [*docs.columns, name]) for x in ("marked_id", "marked_of"))
    known = docs.where(F.col("doc_id").isNotNull())
    # the texts of the first join and those of the last are dealt by doc_id by one and the same exchange
    own = typed(known, doc_id="bigint", text="string")
    several = bool(own.groupBy("doc_id").count().where("count > 1").limit(1).count())
    if several:
        own = own.withColumn("of", F.xxhash64("text")).dropDuplicates(["doc_id", "of"])
    marks = _extended(own, _seeds(own.select("doc_id", "text"))).groupBy("doc_id", *(["of"] if several else [])).agg(F.collect_list(F.struct("at", "bits")).alias(name))
    marks = marks.select(F.col("doc_id").alias(id_), F.col("of").alias(of_), name) if several else marks.select(F.col("doc_id").alias(id_), name)
    same = known["doc_id"].cast("long") == marks[id_]
    out = known.join(marks, same & (marks[of_] == F.xxhash64(known["text"].cast("string"))) if several else same, "left")
    nobody = docs.where(F.col("doc_id").isNull()).withColumn(name, F.lit(None).cast(out.schema[name].dataType))
    return out.select(*docs.columns, name).unionByName(nobody)


def _kept(raw: bytes, marks: list[dict] | None) -> tuple[int, int, bytes, bool]:
    words = raw.split()
    if not marks:
        return len(words), 0, b" ".join(words), False
    gone = _covered(len(words), marks)
    return len(words), int(gone.sum()), b" ".join(compress(words, (~gone).tolist())), bool(gone.any())


def digests(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_removed and kept_sha256 of every row; nulls, empties and repeats as ``marked`` has them."""

    def run(batches):
        for batch in batches:
            data, offsets = strings(batch.column(1))
            marks, rows = batch.column(2), []
            for at, to in slabs(offsets):
                for i in range(at, to):
                    n, gone, kept, _ = _kept(data[offsets[i] : offsets[i + 1]].tobytes(), marks[i].as_py())
                    rows.append((n, gone, hashlib.sha256(kept).hexdigest()))
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.string())))], ["doc_id", "n_words", "n_removed", "kept_sha256"])

    own = typed(docs, doc_id="bigint", text="string")
    return marked(own).select("doc_id", "text", "marks").mapInArrow(lean(run), "doc_id long, n_words long, n_removed long, kept_sha256 string")


def without_repeats(docs: DataFrame) -> DataFrame:
    """``docs`` with the repeated words taken out of the texts that have some; other texts stay as they are.

    Documents of which nothing is left are gone; ``n_chars``, if there, is that of the new text.
    Nulls, empty texts, repeats and empty tables are those of ``marked``; columns of any name stay.
    """
    schema, names = docs.schema, docs.columns
    marks_of = unused("marks", names)
    place = names.index("text")

    def run(batches):
        for batch in batches:
            data, offsets = strings(batch.column(place).cast(pa.string()))
            marks, texts, stay = batch.column(len(names)), [], []
            for i in range(batch.num_rows):
                own = marks[i].as_py()
                if not own:
                    texts.append(batch.column(place)[i].as_py())
                    stay.append(True)
                    continue
                _, _, kept, changed = _kept(data[offsets[i] : offsets[i + 1]].tobytes(), own)
                texts.append(kept.decode() if changed else batch.column(place)[i].as_py())
                stay.append(bool(kept) or not changed)
            columns = [batch.column(i) for i in range(len(names))]
            columns[place] = pa.array(texts, batch.schema.field(place).type)
            yield pa.RecordBatch.from_arrays(columns, names).filter(pa.array(stay, pa.bool_()))

    out = marked(docs, marks_of).select(*names, marks_of).mapInArrow(lean(run), schema)
    if "n_chars" in names:
        out = out.withColumn("n_chars", F.coalesce(F.length("text"), F.lit(0)).cast(schema["n_chars"].dataType))
    return out.select(*names)


def op7_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without the words of 13-word windows that a document of smaller id has too."""
    return digests(table(spark, sf_dir, "documents").select("doc_id", "text"))


ORACLE = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
g AS (
  SELECT doc_id, i, array_to_string(ws[i:i + 12], ' ') AS win
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 11)) AS i FROM w WHERE len(ws) >= 13)),
m AS (SELECT win, min(doc_id) AS least FROM g GROUP BY win),
r AS (SELECT DISTINCT g.doc_id, g.i + o.o AS p FROM g JOIN m USING (win), (SELECT unnest(range(0, 13)) AS o) o WHERE m.least < g.doc_id),
t AS (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS p FROM w),
k AS (
  SELECT t.doc_id, count(*) AS n_words, count(r.p) AS n_removed,
    coalesce(string_agg(t.word, ' ' ORDER BY t.p) FILTER (WHERE r.p IS NULL), '') AS kept
  FROM t LEFT JOIN r ON r.doc_id = t.doc_id AND r.p = t.p GROUP BY t.doc_id)
SELECT w.doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM w LEFT JOIN k ON k.doc_id = w.doc_id
"""
