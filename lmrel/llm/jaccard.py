"""N-gram Jaccard join by R-trees of count vectors, down to connected classes.

Shingles are hashed into groups; a set's group counts are a point, and two sets share at most the
sum of the coordinate minima of their points.  Sets meet where they share one of their PREFIX
shingles of least hash (or the shorter prefix that any order of shingles makes exact).  There an
R-tree of the points (boxes with both corners, level by level) finds the pairs that the bound lets pass, and
what is already connected is not compared again, so a group of g near copies gives at most g - 1
links.  The classes of these possible links are then settled by the same search with the exact
overlap of the sets in place of the bound.

Miss probability: the PREFIX shingles of least hash of a union are a uniform sample of it, and one
that lies in both sets is in both prefixes, so a pair at the threshold fails to meet with
probability 0.25 ** PREFIX < 2 ** -63, as rare as equal 64-bit fingerprints of different shingles.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import components, lean, reliable, table
from .grams import each_slab, window_hashes

SHINGLE, PREFIX, LEAST_GROUPS, MOST_GROUPS = 5, 32, 64, 4096
#: Rows of a tile and boxes of a box of the tree.
TILE, FANOUT = 64, 8
#: Rows of a bucket, and shingles of a class, beyond which it is split into blocks.
BUCKET_ROWS, CLASS_SHINGLES = 20_000, 3_000_000
#: Sets of a class of many blocks that are compared in all of its blocks.
HUBS = 16
#: Bits of the sieve that keeps texts of no class out of a shuffle; it is broadcast as SIEVE_BITS / 64 rows at most.
SIEVE_BITS = 1 << 24
_U = np.uint64


def shingle_sets(column: pa.Array, width: int = SHINGLE) -> Iterator[np.ndarray]:
    """The sorted distinct shingle fingerprints of each text; fewer words give one shingle, none an empty set."""
    for at, to, words, bounds in each_slab(column, lower=True):
        windows = window_hashes(words, width)
        for a, z in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
            if z - a >= width:
                yield np.unique(windows[a : z - width + 1])
            else:
                yield window_hashes(words[a:z], z - a) if z > a else np.zeros(0, np.uint64)


def groups_of(n: int) -> int:
    """Groups of a set of n shingles: about n / 4, a power of two, so finer counts fold into coarser ones."""
    return min(MOST_GROUPS, max(LEAST_GROUPS, 1 << max(0, (int(n) - 1).bit_length() - 2)))


def point(shingles: np.ndarray) -> np.ndarray:
    g = groups_of(len(shingles))
    return np.bincount(((shingles >> _U(17)) & _U(g - 1)).astype(np.int64), minlength=g)


def packed(p: np.ndarray) -> bytes:
    return b"\0" + p.astype(np.uint8).tobytes() if p.max(initial=0) < 256 else b"\1" + p.astype(np.uint32).tobytes()


def unpacked(row: bytes) -> np.ndarray:
    return np.frombuffer(row, dtype=np.uint32 if row[0] else np.uint8, offset=1)


def folded(rows: list[np.ndarray], groups: int) -> np.ndarray:
    """The points of the rows at ``groups`` groups, which each of them has or more."""
    out = np.stack([r if len(r) == groups else r.reshape(-1, groups).sum(axis=0) for r in rows])
    return out.astype(np.uint16) if out.max(initial=0) < 1 << 16 else out.astype(np.uint32)


def profiles(docs: DataFrame) -> DataFrame:
    """doc_id, n (set size), set fingerprint (h1, h2), prefix keys and packed point of every text."""

    def run(batches):
        for batch in batches:
            rows = []
            for s in shingle_sets(batch.column(1)):
                h = np.frombuffer(hashlib.blake2b(s.tobytes(), digest_size=16).digest(), dtype=np.int64)
                n = len(s)
                rows.append((n, int(h[0]), int(h[1]), s[: min(PREFIX, n - -(-3 * n // 4) + 1)].view(np.int64) if n else s.view(np.int64), packed(point(s))))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds))], ["doc_id", "n", "h1", "h2", "keys", "point"])

    own = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return own.mapInArrow(lean(run), "doc_id long, n long, h1 long, h2 long, keys array<long>, point binary")


class Forest:
    """Union-find whose unions are the links given out."""

    def __init__(self, n: int, label: np.ndarray | None = None):
        self.parent = np.arange(n)
        if label is not None:
            _, first, inverse = np.unique(label, return_index=True, return_inverse=True)
            self.parent = first[inverse]
        self.links: list[tuple[int, int]] = []

    def root(self, i: int) -> int:
        p = self.parent
        while p[i] != i:
            p[i] = p[p[i]]
            i = p[i]
        return int(i)

    def roots(self, index: np.ndarray) -> np.ndarray:
        r = self.parent[index]
        while True:
            up = self.parent[r]
            if (up == r).all():
                self.parent[index] = r
                return r
            r = up

    def join(self, i: int, j: int) -> None:
        a, b = self.root(i), self.root(j)
        if a != b:
            self.parent[max(a, b)] = min(a, b)
            self.links.append((i, j))


Check = Callable[[int, np.ndarray], np.ndarray]


def fold(m: np.ndarray, groups: int) -> np.ndarray:
    """Points or corners (last axis) at ``groups`` groups."""
    return m if m.shape[-1] == groups else m.reshape(*m.shape[:-1], -1, groups).sum(axis=-2)


class Box:
    """A node of the tree: a tile of rows with their points, or up to FANOUT boxes below it.

    Its corners are the least and the largest count of its rows in each group; folded corners stay
    bounds of the folded points.
    """

    def __init__(self, n: np.ndarray, rows: np.ndarray, points: np.ndarray | None = None, kids: list["Box"] | None = None):
        self.rows, self.points, self.kids = rows, points, kids or []
        self.low, self.high = int(n[rows].min()), int(n[rows].max())

    @cached_property
    def upper(self) -> np.ndarray:
        return self.points.max(axis=0).astype(np.int32) if not self.kids else np.max([k.upper for k in self.kids], axis=0)

    @cached_property
    def lower(self) -> np.ndarray:
        return self.points.min(axis=0).astype(np.int32) if not self.kids else np.min([k.lower for k in self.kids], axis=0)


def box_tree(n: np.ndarray, points: list[np.ndarray], rows: np.ndarray, groups: int) -> Box:
    """The root over ``rows``, in packing order, whose points have ``groups`` groups."""
    cut = lambda items, size: [items[i : i + size] for i in range(0, len(items), size)]
    boxes = [Box(n, t, folded([points[r] for r in t.tolist()], groups)) for t in cut(rows, TILE)]
    while len(boxes) > 1:
        boxes = [Box(n, np.concatenate([b.rows for b in kids]), kids=kids) for kids in cut(boxes, FANOUT)]
    return boxes[0]


def may_link(xs: list[Box], ys: list[Box], groups: int) -> np.ndarray:
    """For every two boxes whether sizes and corners let a row of the one link with a row of the other.

    Two rows share at most the sum of the minima of the upper corners, and a row shares nothing of
    what its box's lower corner has beyond the other box's upper corner.
    """
    (xl, xh), (yl, yh) = (np.array([(b.low, b.high) for b in side]).T for side in (xs, ys))
    xl, xh = xl[:, None], xh[:, None]
    (x0, x1), (y0, y1) = ((fold(np.stack([b.lower for b in side]), groups), fold(np.stack([b.upper for b in side]), groups)) for side in (xs, ys))
    most = np.minimum(x1[:, None], y1[None]).sum(axis=2, dtype=np.int64)
    beyond_x = np.maximum(x0[:, None] - y1[None], 0).sum(axis=2, dtype=np.int64)
    beyond_y = np.maximum(y0[None] - x1[:, None], 0).sum(axis=2, dtype=np.int64)
    return (7 * most >= 3 * (xl + yl)) & (4 * xh - 3 * yl >= 7 * beyond_x) & (4 * yh - 3 * xl >= 7 * beyond_y)


def tree_links(n: np.ndarray, points: list[np.ndarray], check: Check | None = None, label: np.ndarray | None = None) -> list[tuple[int, int]]:
    """A spanning forest of the pairs whose bound (and, if given, ``check``) reaches the threshold.

    Rows of one number of groups make one tree, packed by size and then by a coordinate.  Trees are
    joined from their roots down, each with itself first: two boxes are opened only if sizes and
    corners let a link exist and their rows are not connected throughout.  Boxes of two trees are
    compared at the groups of the smaller sizes.  Rows of equal ``label`` are connected from the start.
    """
    forest = Forest(len(n), label)
    half = np.array([p[: len(p) // 2].sum() / max(1, p.sum()) for p in points])
    levels = np.array([len(p) for p in points])
    trees = []
    for g in np.unique(levels).tolist():
        own = np.flatnonzero(levels == g)
        own = own[np.argsort(n[own], kind="stable")]
        own = own[np.lexsort((half[own], np.arange(len(own)) // (FANOUT * TILE)))]
        trees.append((box_tree(n, points, own, g), g))

    def compare(x: Box, y: Box, g: int) -> None:
        rx, ry = forest.roots(x.rows), forest.roots(y.rows)
        shared = np.minimum(x.points[:, None, :], fold(y.points, g)[None, :, :]).sum(axis=2, dtype=np.int64)
        reach = (7 * shared >= 3 * (n[x.rows][:, None] + n[y.rows][None, :])) & (rx[:, None] != ry[None, :])
        if x is y:
            reach = np.triu(reach, 1)
        for i in np.flatnonzero(reach.any(axis=1)):
            a, b = int(x.rows[i]), y.rows[reach[i]]
            b = b[forest.roots(b) != forest.root(a)]
            if check is not None and len(b):
                b = b[check(a, b)]
            for other in b.tolist():
                forest.join(a, other)

    def meet(x: Box, y: Box, g: int) -> None:
        first = forest.root(int(x.rows[0]))
        if (forest.roots(x.rows) == first).all() and (x is y or (forest.roots(y.rows) == first).all()):
            return
        if not x.kids and not y.kids:
            compare(x, y, g)
            return
        xs, ys = x.kids or [x], y.kids or [y]
        if x is y:
            for box in xs:
                meet(box, box, g)
        open_ = may_link(xs, ys, g)
        for i, j in zip(*np.nonzero(np.triu(open_, 1) if x is y else open_)):
            meet(xs[i], ys[j], g)

    for at, (x, g) in enumerate(trees):
        meet(x, x, g)
        for y, _ in trees[at + 1 :]:
            if may_link([x], [y], g)[0, 0]:
                meet(x, y, g)
    return forest.links


def _small_links(n: np.ndarray, points: list[np.ndarray], begin: np.ndarray, size: np.ndarray) -> list[tuple[int, int]]:
    """The same over many small buckets (first rows and sizes) at once, with the bound alone."""
    forest, levels = Forest(len(n)), np.array([len(p) for p in points])
    for g in np.unique(size):
        a, b = np.triu_indices(int(g), 1)
        first = begin[size == g]
        x, y = (first[:, None] + a).ravel(), (first[:, None] + b).ravel()
        fit = 4 * np.minimum(n[x], n[y]) >= 3 * np.maximum(n[x], n[y])
        x, y = x[fit], y[fit]
        at = np.minimum(levels[x], levels[y])
        for k in np.unique(at).tolist():
            px, py = x[at == k], y[at == k]
            rows, where = np.unique(np.concatenate([px, py]), return_inverse=True)
            matrix = folded([points[r] for r in rows.tolist()], k)
            for part in np.array_split(np.arange(len(px)), max(1, len(px) * k // 4_000_000)):
                shared = np.minimum(matrix[where[part]], matrix[where[len(px) + part]]).sum(axis=1, dtype=np.int64)
                ok = 7 * shared >= 3 * (n[px[part]] + n[py[part]])
                for u, v in zip(px[part][ok].tolist(), py[part][ok].tolist()):
                    forest.join(u, v)
    return forest.links


def grouped(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.Table]:
    """Tables of whole groups from rows sorted by their first ``keys`` columns; small groups come many at a time."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        change = np.zeros(batch.num_rows, dtype=bool)
        for k in range(keys):
            v = batch.column(k).to_numpy(zero_copy_only=False)
            change[1:] |= v[1:] != v[:-1]
            if held:
                change[0] |= v[0] != held[-1].column(k)[held[-1].num_rows - 1].as_py()
        cut = np.flatnonzero(change)
        if len(cut):
            last = int(cut[-1])
            head = [*held, batch.slice(0, last)]
            held = []
            if sum(x.num_rows for x in head):
                yield pa.Table.from_batches(head).combine_chunks()
            batch = batch.slice(last)
        held.append(batch)
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _bounds(part: pa.Table, keys: int) -> np.ndarray:
    change = np.ones(part.num_rows, dtype=bool)
    change[1:] = False
    for k in range(keys):
        v = part.column(k).to_numpy()
        change[1:] |= v[1:] != v[:-1]
    return np.append(np.flatnonzero(change), part.num_rows)


def _pairs_of_blocks(rows: DataFrame, blocks: str) -> DataFrame:
    """Rows of a group of many blocks, once for every pair of blocks that their own block is in."""
    own = F.pmod(F.xxhash64(F.lit(11), F.col("rep")), F.col(blocks)).cast("int")
    rows = rows.withColumn("own", own).withColumn("peer", F.explode(F.sequence(F.lit(0), F.col(blocks) - 1)))
    return rows.withColumn("i", F.least("own", "peer")).withColumn("j", F.greatest("own", "peer")).drop("own", "peer", blocks)


def possible_links(sets: DataFrame) -> DataFrame:
    """(a, b): a spanning forest, bucket by bucket, of the pairs that the bound does not rule out.

    ``sets`` has rep, n, keys and point.  Only keys of two sets or more are kept; buckets beyond
    BUCKET_ROWS are split into pairs of blocks, so a task holds at most two blocks.
    """
    met = sets.select("rep", F.explode("keys").alias("key"))
    shared = met.groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c > 1")
    rows = met.join(shared, "key").withColumn("blocks", F.ceil(F.col("c") / BUCKET_ROWS).cast("int"))
    rows = _pairs_of_blocks(rows, "blocks").join(sets.select("rep", "n", "point"), "rep")
    rows = rows.select("key", "i", "j", "n", "rep", "point").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "n", "rep")

    def run(batches):
        for part in grouped(batches, 3):
            bounds = _bounds(part, 3)
            n, rep = part.column("n").to_numpy(), part.column("rep").to_numpy()
            size, links = np.diff(bounds), []
            small = np.flatnonzero(size <= 16)
            at = np.concatenate([np.arange(bounds[g], bounds[g + 1]) for g in small]) if len(small) else np.zeros(0, np.int64)
            if len(at):
                for piece in np.array_split(small, max(1, len(at) // 20_000)):
                    rows = np.concatenate([np.arange(bounds[g], bounds[g + 1]) for g in piece])
                    found = _small_links(n[rows], [unpacked(r) for r in part.column("point").take(rows).to_pylist()], np.cumsum(size[piece]) - size[piece], size[piece])
                    links += [(rows[a], rows[b]) for a, b in found]
            for g in np.flatnonzero(size > 16):
                x, y = int(bounds[g]), int(bounds[g + 1])
                found = tree_links(n[x:y], [unpacked(r) for r in part.column("point").slice(x, y - x).to_pylist()])
                links += [(x + a, x + b) for a, b in found]
            pair = np.array(links, dtype=np.int64).reshape(-1, 2)
            if len(pair):
                ends = np.unique(np.sort(rep[pair], axis=1), axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(ends[:, 0]), pa.array(ends[:, 1])], ["a", "b"])

    return rows.mapInArrow(lean(run), "a long, b long").distinct()


def sifted(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """``docs`` without most rows whose ``node`` is not in ``wanted``, and with all whose node is.

    A bitmap of hashed nodes, of SIEVE_BITS bits however many they are, is broadcast; where they are
    so many that it fills up, more rows pass.  The caller joins exactly afterwards.
    """
    slot = f"pmod(xxhash64(node), {SIEVE_BITS}L)"
    bits = wanted.groupBy(F.expr(f"{slot} div 64").alias("word")).agg(F.expr(f"bit_or(shiftleft(1L, cast({slot} % 64 as int)))").alias("bits"))
    seen = docs.withColumn("word", F.expr(f"{slot} div 64")).join(F.broadcast(bits), "word")
    return seen.where(F.expr(f"shiftright(bits, cast({slot} % 64 as int)) & 1 = 1")).select(*docs.columns)


def exact_links(docs: DataFrame, members: DataFrame) -> DataFrame:
    """(a, b): links that join what is not joined yet, cell by cell, where the exact overlap reaches the threshold.

    ``docs`` has doc_id and text; ``members`` has component, node, label (nodes of one label are
    joined already) and cells, the places (i, j) where a node is compared with the others sent
    there.  The upper 48 bits of the fingerprints tell the shingles of two sets apart.
    """

    def sets(batches):
        for batch in batches:
            found = list(shingle_sets(batch.column(3)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array([len(s) for s in found], pa.int64()), pa.array([s.view(np.uint8).reshape(-1, 8)[:, 2:].tobytes() for s in found], pa.binary()), batch.column(4)], ["component", "rep", "label", "n", "shingles", "cells"])

    texts = sifted(docs.select(F.col("doc_id").cast("long").alias("node"), F.col("text").cast("string")), members).join(members, "node")
    rows = texts.select("component", F.col("node").alias("rep"), "label", "text", "cells").mapInArrow(lean(sets), "component long, rep long, label long, n long, shingles binary, cells array<struct<i:int,j:int>>")
    rows = rows.withColumn("cell", F.explode("cells")).select("component", "cell.i", "cell.j", "n", "rep", "label", "shingles")
    rows = rows.repartition("component", "i", "j").sortWithinPartitions("component", "i", "j", "n", "rep")

    def run(batches):
        for part in grouped(batches, 3):
            bounds = _bounds(part, 3)
            n, rep, label, raw = part.column("n").to_numpy(), part.column("rep").to_numpy(), part.column("label").to_numpy(), part.column("shingles")
            ends = []
            for x, y in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                if (label[x:y] == label[x]).all():
                    continue
                wide = np.zeros((int(n[x:y].sum()), 8), dtype=np.uint8)
                wide[:, 2:] = np.frombuffer(b"".join(v.as_py() for v in raw.slice(x, y - x)), dtype=np.uint8).reshape(-1, 6)
                flat = wide.reshape(-1).view(np.uint64)
                points = [point(s) for s in np.split(flat, np.cumsum(n[x:y])[:-1])]
                _, ids = np.unique(flat, return_inverse=True)
                own, start, mark = n[x:y], np.concatenate([[0], np.cumsum(n[x:y])]), np.zeros(ids.max() + 1, dtype=np.int64)

                def check(a: int, others: np.ndarray, own=own, start=start, mark=mark, ids=ids) -> np.ndarray:
                    mark[ids[start[a] : start[a + 1]]] = 1
                    both = np.array([mark[ids[start[b] : start[b + 1]]].sum() for b in others.tolist()])
                    mark[ids[start[a] : start[a + 1]]] = 0
                    return 100 * both >= 75 * (own[a] + own[others] - both)

                ends += [(rep[x + a], rep[x + b]) for a, b in tree_links(own, points, check, label[x:y])]
            if ends:
                pair = np.array(ends, dtype=np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1])], ["a", "b"])

    return rows.mapInArrow(lean(run), "a long, b long")


def _block(node: str, blocks: str, seed: int) -> str:
    return f"cast(pmod(xxhash64({seed}, {node}), {blocks}) as int)"


def settled_classes(docs: DataFrame, possible: DataFrame) -> DataFrame:
    """(node, component) of the true links within the classes of possible links.

    ``docs`` has doc_id and text; ``possible`` has node, n (shingles) and component.  A class of
    more than CLASS_SHINGLES shingles is dealt into blocks.  First each block is settled by itself,
    with up to HUBS sets of the class that go to all of its blocks and so tie the blocks together.
    Then only the sets outside the class's largest part (the loose ones) still meet all others:
    blocks of loose sets against blocks of all sets.  A class that is one part after the first round
    is sent once, and no cell holds more than two blocks.
    """
    total = possible.groupBy("component").agg(F.ceil(F.sum("n") / CLASS_SHINGLES).cast("int").alias("blocks"))
    members = reliable(possible.join(total, "component").select("component", "node", "n", "blocks"))
    large = members.where("blocks > 1")
    hubs = large.groupBy("component", F.expr(_block("node", str(HUBS), 5)).alias("k")).agg(F.expr("min_by(node, xxhash64(7, node))").alias("node")).select("node", F.lit(True).alias("hub"))
    own = _block("node", "blocks", 11)
    cells = F.expr(f"transform(CASE WHEN hub THEN sequence(0, blocks - 1) ELSE array({own}) END, b -> struct(b AS i, b AS j))")
    first = members.join(hubs, "node", "left").select("component", "node", F.col("node").alias("label"), cells.alias("cells"))
    settled = reliable(components(exact_links(docs, first)))
    part = large.join(settled.withColumnRenamed("component", "part"), "node", "left").withColumn("label", F.coalesce("part", "node"))
    main = part.groupBy("component", "label").count().groupBy("component").agg(F.expr("max_by(label, struct(count, label))").alias("main"))
    part = part.join(main, "component").withColumn("loose", F.expr("label <> main"))
    apart = part.where("loose").groupBy("component").agg(F.ceil(F.sum("n") / CLASS_SHINGLES).cast("int").alias("loose_blocks"))
    rest = part.join(apart, "component").withColumn("own", F.expr(own)).withColumn("own_loose", F.expr(_block("node", "loose_blocks", 13)))
    every = "transform(sequence(0, loose_blocks - 1), l -> struct(l AS i, own AS j))"
    cells = F.expr(f"CASE WHEN loose THEN array_union({every}, transform(sequence(0, blocks - 1), b -> struct(own_loose AS i, b AS j))) ELSE {every} END")
    rest = reliable(rest.select("component", "node", "label", cells.alias("cells")))
    if not rest.limit(1).count():
        return settled
    more = exact_links(docs, rest)
    return components(settled.select(F.col("node").alias("a"), F.col("component").alias("b")).union(more))


def near_duplicate_classes(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles and component_id of every row of ``docs`` (doc_id, text).

    Documents link when 100 * shared >= 75 * united shingles; a class is everything reachable, its
    id the smallest doc_id.  Null and empty texts have no shingles and are their own class; a null
    doc_id is in no class (component_id null); repeated rows have equal sets and so one class; a
    doc_id with several texts joins the classes of all of them; whole texts count, however long; an
    empty table gives an empty result.  Only doc_id and text are read.
    """
    own = reliable(profiles(docs))
    real = own.where("n > 0 AND doc_id IS NOT NULL")
    classes = reliable(real.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "n", "keys", "point")).alias("r")).select("h1", "h2", F.col("r.doc_id").alias("rep"), F.col("r.n").alias("n"), F.col("r.keys").alias("keys"), F.col("r.point").alias("point")))
    possible = components(possible_links(classes))
    sizes = classes.groupBy(F.col("rep").alias("node")).agg(F.max("n").alias("n"))
    settled = settled_classes(docs, possible.join(sizes, "node"))
    named = classes.select("h1", "h2", "rep").join(settled, F.col("rep") == F.col("node"), "left").select("h1", "h2", F.coalesce("component", "rep").alias("component"))
    out = own.join(named, ["h1", "h2"], "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.when(F.col("doc_id").isNotNull(), F.col("component"))).otherwise(F.col("doc_id")).alias("component_id"))


def one_of_each_class(docs: DataFrame) -> DataFrame:
    """``docs`` without the documents that are in a class with a smaller doc_id; rows of null doc_id stay.

    Rows equal in doc_id and text are one document, of which the row stays whose other columns are
    least as JSON.  A doc_id with several texts is one document of several sets: all its texts stay
    or go together.  Null and empty texts are alone in their class and stay; an empty table stays
    empty; columns of any name are kept.
    """
    classes = near_duplicate_classes(docs.select("doc_id", "text"))
    gone = classes.where(F.col("component_id") < F.col("doc_id")).select("doc_id").distinct()
    kept = docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
    known = docs.where("doc_id IS NOT NULL")
    if known.groupBy("doc_id").count().where("count > 1").limit(1).count():
        whole = F.struct(*docs.columns)
        single = kept.where("doc_id IS NOT NULL").groupBy("doc_id", "text").agg(F.min_by(whole, F.to_json(whole)).alias("r")).select("r.*")
        kept = single.unionByName(kept.where("doc_id IS NULL"))
    return kept


def op6_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The class of every document under word 5-gram Jaccard links of 0.75 or more."""
    return near_duplicate_classes(table(spark, sf_dir, "documents").select("doc_id", "text"))


ORACLE = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws
  FROM documents WHERE text IS NOT NULL),
s AS (
  SELECT DISTINCT doc_id, array_to_string(ws[i:i + 4], ' ') AS sh
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 4, 1) + 1)) AS i FROM w WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
l AS (
  SELECT a.doc_id AS a, b.doc_id AS b
  FROM s a JOIN s b ON a.sh = b.sh AND a.doc_id <> b.doc_id
  JOIN n na ON na.doc_id = a.doc_id JOIN n nb ON nb.doc_id = b.doc_id
  GROUP BY a.doc_id, b.doc_id, na.n, nb.n
  HAVING 100 * count(*) >= 75 * (na.n + nb.n - count(*))),
r AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
c AS (SELECT a, min(b) AS component_id FROM r GROUP BY a)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, c.component_id
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id JOIN c ON c.a = d.doc_id
"""
