"""Mixing sources to target weights: equal-token blocks dealt by highest quotients.

Token blocks are apportioned to the sources by the divisors 1, 3, 5, ..., each source's blocks to
its shards in the same way, and a shard takes its quota as whole passes plus a seeded choice of
blocks.  Everything is DataFrame operations; the driver sees one row per source and at most
``MAX_SHARDS`` per source, and broadcasts them only up to ``BROADCAST_ROWS``.
"""

from __future__ import annotations

import heapq
import math
from fractions import Fraction

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import WORD, reliable, table

#: Rows of a shard, and the most shards of a source (then shards grow instead).
SHARD_ROWS, MAX_SHARDS = 2000, 4096
#: A corpus is cut into this many blocks, but a block has 1 word at least and MAX_BLOCK at most.
BLOCKS, MAX_BLOCK = 1 << 20, 256
#: Rows of quotas that are broadcast; more of them are joined by a shuffle.
BROADCAST_ROWS = 50_000


def targets(sizes: dict, weights: tuple[int, ...] = (5, 2, 1), repeats: int = 3) -> dict:
    """Exact target of each source: weights by code-point order (None last), at most ``repeats`` sizes each.

    What a stopped source leaves is shared by weight among the others, until none is above.  A source
    of size 0 has target 0; no sources give no targets.
    """
    order = sorted((s for s in sizes if s is not None)) + [s for s in sizes if s is None]
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    left, free, out = Fraction(sum(sizes.values())), set(order), {}
    while free:
        unit = left / sum(weight[s] for s in free)
        over = {s for s in free if unit * weight[s] > repeats * sizes[s]}
        for s in over or free:
            out[s] = Fraction(repeats * sizes[s]) if over else unit * weight[s]
        left -= sum(out[s] for s in over)
        free -= over or free
    return out


def apportion(weights: list[Fraction | int], seats: int, most: list[int] | None = None) -> list[int]:
    """Seats by highest quotients weight / (2n + 1), ties to the earlier; at most ``most`` each.

    The quotas at a divisor d are round(weight / d); d is found by bisection over whole numbers,
    which leaves fewer seats than parties, and those are dealt one by one from a heap.  So any
    number of seats costs the same, n log n in all.  No parties, no seats or only weights of 0
    give zeros.
    """
    n = len(weights)
    most = most or [seats] * n
    seats = min(seats, sum(most[i] for i in range(n) if weights[i] > 0))
    if not n or seats <= 0:
        return [0] * n
    unit = math.lcm(*(Fraction(w).denominator for w in weights))
    whole = [int(w * unit) for w in weights]
    scale = 4 * (max(most) + 1) * n  # a divisor is d / scale: fine enough to tell the last seats apart but for n of them
    count = lambda d: [min(m, (w * scale + d) // (2 * d)) if w else 0 for w, m in zip(whole, most)]
    low, high = 1, 2 * max(whole) * scale + 1  # at high nobody has a seat
    while high - low > 1:
        mid = (low + high) // 2
        if sum(count(mid)) > seats:
            low = mid
        else:
            high = mid
    got = count(high)
    queue = [(-Fraction(w, 2 * g + 1), i) for i, (w, g, m) in enumerate(zip(whole, got, most)) if w and g < m]
    heapq.heapify(queue)
    for _ in range(seats - sum(got)):
        _, i = heapq.heappop(queue)
        got[i] += 1
        if got[i] < most[i]:
            heapq.heappush(queue, (-Fraction(whole[i], 2 * got[i] + 1), i))
    return got


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def plan(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), repeats: int = 3, seed: int = 17, prefix: str = "mix_") -> DataFrame:
    """Adds to every row of ``docs`` (doc_id, source, ``{prefix}size``) what the mix takes of it.

    Added, all with the prefix: source_size, target, shard, passes (whole copies), spans (array of
    the word ranges taken once more), taken (words, repeats counted).  A row of no words takes 0;
    an empty table stays empty; rows with null doc_id or null source count like others; equal rows
    are separate rows of the order.  Columns of other names are carried along; one that has the name
    of an added column gives way to it (``mixed_documents`` takes a prefix that no column has).
    """
    spark, p = docs.sparkSession, prefix
    docs = docs.drop(*(c for c in docs.columns if c.lower().startswith(p) and c != f"{p}size"))
    size = F.col(f"{p}size")
    key = F.xxhash64(F.lit(seed), F.col("doc_id"), size)
    stats = docs.groupBy("source").agg(F.sum(size).alias("s"), F.count(F.lit(1)).alias("n")).collect()
    sizes, rows = {r.source: r.s for r in stats}, {r.source: r.n for r in stats}
    goal = targets(sizes, weights, repeats)
    total = sum(sizes.values())
    block = min(MAX_BLOCK, max(1, total // BLOCKS))
    order = sorted((s for s in sizes if s is not None)) + [s for s in sizes if s is None]
    quota = dict(zip(order, apportion([goal[s] for s in order], round(Fraction(total, block)), [repeats * sizes[s] // block + 1 for s in order])))
    shards = {s: min(MAX_SHARDS, max(1, math.ceil(rows[s] / SHARD_ROWS))) for s in order}

    def joined(df: DataFrame, right: list[tuple], schema: str, on: list[str]) -> DataFrame:
        small = spark.createDataFrame(right, schema)
        other = [f"{p}on_{c.removeprefix(p)}" for c in on]
        same = [df[c].eqNullSafe(small[o]) for c, o in zip(on, other)]
        test = same[0]
        for x in same[1:]:
            test = test & x
        return df.join(F.broadcast(small) if len(right) <= BROADCAST_ROWS else small, test, "left").drop(*other)

    kind = f"{p}on_source string"
    out = joined(docs, [(s, shards[s], sizes[s], float(goal[s])) for s in order], f"{kind}, {p}n_shards int, {p}source_size long, {p}target double", ["source"])
    out = out.withColumn(f"{p}key", key).withColumn(f"{p}shard", F.pmod(F.xxhash64(F.col(f"{p}key")), F.col(f"{p}n_shards")).cast("int"))
    per = {}
    for r in out.groupBy("source", f"{p}shard").agg(F.sum(size).alias("s")).collect():
        per.setdefault(r.source, {})[r[f"{p}shard"]] = r.s
    made = []
    for s in order:
        ids = sorted(per.get(s, {}))
        own = [per[s][i] for i in ids]
        for i, words, q in zip(ids, own, apportion(own, quota[s], [repeats * max(1, round(w / block)) if w else 0 for w in own])):
            blocks = max(1, round(words / block)) if words else 1
            step = next(a for a in range(max(1, int(blocks * 0.618)), blocks + 2) if math.gcd(a, blocks) == 1)
            made.append((s, i, words, blocks, q // blocks, q % blocks, step % blocks if blocks > 1 else 1, hash_int(seed, i) % blocks))
    made = made or [(None, -1, 0, 1, 0, 0, 1, 0)]
    out = joined(out, made, f"{kind}, {p}on_shard int, {p}words long, {p}blocks long, {p}passes int, {p}rest long, {p}step long, {p}start long", ["source", f"{p}shard"])
    w = Window.partitionBy("source", f"{p}shard").orderBy(f"{p}key", "doc_id", f"{p}size").rowsBetween(Window.unboundedPreceding, -1)
    out = out.withColumn(f"{p}at", F.coalesce(F.sum(size).over(w), F.lit(0)))
    at, words, blocks = (F.col(f"{p}{x}") for x in ("at", "words", "blocks"))
    first = F.expr(f"(({p}at + 1) * {p}blocks - 1) div {p}words")  # the block that holds the row's first word
    last = F.expr(f"(({p}at + {p}size) * {p}blocks - 1) div {p}words")

    def whole(x: Column) -> Column:
        return ((x - F.pmod(x, blocks)) / blocks).cast("long")

    def span(j: Column) -> Column:
        begin, end = whole(j * words), whole((j + 1) * words)
        return F.struct((F.greatest(begin, at) - at).alias("start"), (F.least(end, at + size) - at).alias("end"))

    chosen = F.filter(F.sequence(first, last), lambda j: F.pmod(j * F.col(f"{p}step") + F.col(f"{p}start"), blocks) < F.col(f"{p}rest"))
    spans = F.when(size > 0, F.transform(chosen, span)).otherwise(F.array().cast("array<struct<start:bigint,end:bigint>>"))
    out = out.withColumn(f"{p}spans", spans)
    extra = F.aggregate(F.col(f"{p}spans"), F.lit(0).cast("long"), lambda a, x: a + x["end"] - x["start"])
    out = out.withColumn(f"{p}taken", (F.col(f"{p}passes") * size + extra).cast("long"))
    return out.drop(*[f"{p}{c}" for c in ("n_shards", "key", "words", "blocks", "rest", "step", "start", "at")])


def hash_int(*parts: int) -> int:
    x = 0x9E3779B97F4A7C15
    for v in parts:
        x = (x ^ (v & (1 << 64) - 1)) * 0xBF58476D1CE4E5B9 % (1 << 64)
        x ^= x >> 31
    return x


def mixed_documents(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), repeats: int = 3, seed: int = 17) -> DataFrame:
    """The mixed corpus: whole copies of the rows and, joined by a space, the words taken once more.

    Columns are those of ``docs``; ``n_chars``, if there, is that of the text given out.  Rows that
    the mix does not take are gone; a document of no words takes no part of any target and stays.
    Null texts have no words and stay null; null sources are a source; repeated rows are taken each
    for itself; an empty table stays empty; columns of any name are kept.
    """
    own = docs.columns
    p = "mix_"
    while any(c.lower().startswith(p) for c in own):
        p = f"_{p}"
    planned = plan(docs.withColumn(f"{p}size", n_words(F.col("text"))), weights, repeats, seed, p)
    words = F.regexp_extract_all(F.col("text"), F.lit(f"({WORD})"), F.lit(1))
    joined = lambda w: F.array_join(F.flatten(F.transform(F.col(f"{p}spans"), lambda s: F.slice(w, s["start"] + 1, s["end"] - s["start"]))), " ")
    part = F.transform(F.array(words), joined)[0]  # the words are found once for a row, not once for a span
    copies = F.when(F.col(f"{p}size") == 0, F.array(F.col("text"))).otherwise(
        F.concat(F.array_repeat(F.col("text"), F.col(f"{p}passes").cast("int")), F.when(F.size(f"{p}spans") > 0, F.array(part)).otherwise(F.array().cast("array<string>")))
    )
    out = planned.withColumn(f"{p}text", F.explode(copies)).withColumn("text", F.col(f"{p}text"))
    if "n_chars" in own:
        out = out.withColumn("n_chars", F.coalesce(F.length("text"), F.lit(0)).cast(docs.schema["n_chars"].dataType))
    return out.select(*own)


def op8_mixing_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document: its size, its source's size and target, and the words the mix takes.

    Null and empty texts have size 0 and are not taken; repeated rows are rows of their own.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", n_words(F.col("text")).alias("mix_size"))
    out = plan(reliable(docs))
    return out.select(
        F.col("doc_id").cast("long"), F.col("mix_size").alias("size"), F.col("mix_source_size").alias("source_size"), F.col("mix_target").alias("target"),
        F.col("mix_taken").alias("taken"), F.col("mix_shard").alias("shard"), F.col("mix_passes").alias("passes"), F.size("mix_spans").alias("blocks"),
    )
