"""Shared pieces of the operators: tables, checkpoints and connected components."""

from __future__ import annotations

import ctypes
import re
import tempfile
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word, as Java's and Python's expressions read it.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def reliable(df: DataFrame) -> DataFrame:
    """``df`` with its lineage cut by a checkpoint in the folder that the cluster names.

    A session in one process (as in tests) that names none gets a temporary folder; a cluster that
    names none is refused, since its executors share no temporary folder.
    """
    context = df.sparkSession.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        named = context.getConf().get("spark.checkpoint.dir")
        if not named and not re.match(r"local(\[|$)", context.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint"))
    return df.checkpoint()


def unused(name: str, taken: Iterable[str]) -> str:
    """``name``, or a longer one where a column has it already (in any case)."""
    have = {c.lower() for c in taken}
    while name.lower() in have:
        name = f"_{name}"
    return name


def typed(df: DataFrame, **kinds: str) -> DataFrame:
    """The named columns, cast where they have another type; the same plan where they have it already, so exchanges are reused."""
    have = dict(df.dtypes)
    return df.select(*(F.col(c) if have[c] == kind else F.col(c).cast(kind).alias(c) for c, kind in kinds.items()))


def give_back() -> None:
    """Hands the memory that a worker has freed back to the system, which its allocators else keep."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """``run`` over a task's Arrow batches, after which an idle worker keeps no freed memory."""

    def task(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return task


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component) of an undirected edge list with columns ``a`` and ``b`` of longs.

    The component is its smallest node.  Alternating star contractions: each round hangs every
    neighbour of a node on the smallest node of its neighbourhood, first for the larger, then for
    the smaller neighbours.  A round is two aggregations with map-side combine and two joins; the
    number of rounds grows with the logarithm of the longest path.  A node occurs in the result
    only if it has an edge to another node.
    """

    def smallest(e: DataFrame) -> DataFrame:
        return e.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))

    def both(e: DataFrame) -> DataFrame:
        return e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))

    now = reliable(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    for _ in range(max_rounds):
        e = both(now)
        large = e.join(smallest(e), "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = smallest(large)
        small = large.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").union(low.select("a", F.col("m").alias("b"))).distinct()
        after = reliable(small)
        moved = after.join(now, ["a", "b"], "left_anti").limit(1).count() + now.join(after, ["a", "b"], "left_anti").limit(1).count()
        now = after
        if not moved:
            break
    else:
        raise RuntimeError("the components did not settle")
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).union(roots)
