"""Answers over a stream: micro-batches ask only inputs that were never asked."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lmrel.operators.executor import with_answers
from lmrel.session import LmCall, Runtime


def lm_stream(stream: DataFrame, call: LmCall, name: str, rt: Runtime, sink: Callable[[DataFrame, int], None], checkpoint: str):
    """Starts a query that hands every micro-batch, with its answers, to ``sink`` and stops when all is read.

    The runtime keeps the answers of earlier batches.  Where it has a cache, that table is the state:
    it outlives a restart, and what a batch held is let go after it, so plans do not grow.
    """
    def batch(df: DataFrame, epoch: int) -> None:
        sink(with_answers(df, call, name, rt), epoch)
        if rt.cache is not None:
            rt.release()

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def tumbling(df: DataFrame, time: str, width: str, by: str, late: str = "10 minutes") -> DataFrame:
    """Counts by window and answer; on a stream rows later than ``late`` are dropped by the watermark."""
    return df.withWatermark(time, late).groupBy(F.window(time, width).alias("w"), by).agg(F.count(F.lit(1)).alias("n"))
