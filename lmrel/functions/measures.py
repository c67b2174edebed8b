"""Quality, cost and saving measures."""

from __future__ import annotations

import os
import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

GPU_HOURLY = 0.18
#: Dollars for a million tokens: text or image in, audio in, out.
API_PRICES = {"text": 0.30, "image": 0.30, "audio": 1.00, "out": 2.50}


def f1(predicted: DataFrame, truth: DataFrame, keys: list[str]) -> dict:
    """precision, recall, f1 over distinct keys; both empty counts as 1."""
    p, t = (d.select(*keys).distinct() for d in (predicted.withColumn("__x", F.lit(1)), truth))
    both = p.withColumn("__p", F.lit(1)).join(t.withColumn("__t", F.lit(1)), keys, "full_outer").agg(F.sum(F.when(F.col("__p").isNotNull() & F.col("__t").isNotNull(), 1).otherwise(0)), F.count("__p"), F.count("__t")).first()
    hit, n, m = both[0] or 0, both[1], both[2]
    if not n and not m:
        return {"precision": 1.0, "recall": 1.0, "f1": 1.0}
    precision, recall = hit / n if n else 0.0, hit / m if m else 0.0
    return {"precision": precision, "recall": recall, "f1": 2 * precision * recall / (precision + recall) if hit else 0.0}


def spearman(df: DataFrame, a: str, b: str) -> float | None:
    """Rank correlation with mean ranks for ties; ranks come from counts by value, not from a sort of all rows."""
    def ranks(c: str) -> DataFrame:
        counts = df.groupBy(F.col(c).alias(f"__{c}")).count()
        w = Window.orderBy(f"__{c}").rowsBetween(Window.unboundedPreceding, 0)
        return counts.withColumn("__to", F.sum("count").over(w)).select(f"__{c}", (F.col("__to") - (F.col("count") - 1) / 2).alias(f"rank_{c}"))

    full = df.where(F.col(a).isNotNull() & F.col(b).isNotNull())
    joined = full.join(ranks(a), F.col(a) == F.col(f"__{a}")).join(ranks(b), F.col(b) == F.col(f"__{b}"))
    return joined.agg(F.corr(f"rank_{a}", f"rank_{b}")).first()[0]


def spearman_quality(rho: float | None, symmetric: bool = False) -> float:
    return 0.0 if rho is None or rho != rho else (rho + 1) / 2 if symmetric else max(0.0, rho)


def agg_quality(p: float, t: float, eps: float = 1e-9, inverse: bool = False) -> float:
    error = abs(p - t)
    return 1 / (1 + error) if inverse else max(0.0, 1 - error / max(abs(t), eps)) if error else 1.0


def local_cost(seconds: float, rate: float = GPU_HOURLY) -> float:
    return seconds * rate / 3600


def api_cost(ledger: list[dict], prices: dict = API_PRICES) -> float:
    return sum(r.get("in_tokens", 0) * prices.get(r.get("modality") or "text", prices["text"]) + r.get("out_tokens", 0) * prices["out"] for r in ledger) / 1e6


def carbon(hours: float, kw: float = 0.336, kg_per_kwh: float = 0.419) -> dict:
    return {"kwh": hours * kw, "kg": hours * kw * kg_per_kwh}


def dup_factor(df: DataFrame, columns: list[str], approximate: bool = False) -> float:
    """Rows for each distinct input; approximate counts cost one pass without a shuffle of values."""
    n, d = df.agg(F.count(F.lit(1)), F.approx_count_distinct(F.struct(*columns)) if approximate else F.count_distinct(F.struct(*columns))).first()
    return n / d if d else 1.0


def win_tie(own: list[float], other: list[float], tolerance: float = 0.02) -> dict:
    wins = sum(a - b > tolerance + 1e-9 for a, b in zip(own, other))
    ties = sum(abs(a - b) <= tolerance + 1e-9 for a, b in zip(own, other))
    return {"win": wins, "tie": ties, "loss": len(own) - wins - ties, "share": (wins + ties) / max(1, len(own))}


def average_system(results: dict[str, dict[str, float | None]], total: bool = False) -> float:
    """Over queries: the mean over the systems that ran it; then the mean (or, for cost, the sum)."""
    queries = {q for r in results.values() for q in r}
    means = [statistics.fmean(v) for q in sorted(queries) if (v := [r[q] for r in results.values() if r.get(q) is not None])]
    return sum(means) if total else statistics.fmean(means)


def count_wins(results: dict[str, dict[str, float | None]], lower: bool = False) -> dict[str, int]:
    """Strict bests of each system."""
    out = dict.fromkeys(results, 0)
    for q in {q for r in results.values() for q in r}:
        have = sorted(((r[q], s) for s, r in results.items() if r.get(q) is not None), reverse=not lower)
        if have and (len(have) == 1 or have[0][0] != have[1][0]):
            out[have[0][1]] += 1
    return out


def coverage(supported: dict[str, int], queries: int = 55) -> dict[str, float]:
    return {s: 100 * n / queries for s, n in supported.items()}


def format_validity(ledger: list[dict]) -> float:
    n = sum(r.get("inputs", 0) for r in ledger)
    return 1 - sum(r.get("malformed", 0) for r in ledger) / n if n else 1.0


def ee_waste(asked: int, rank_of_last_hit: int) -> int:
    return max(0, asked - rank_of_last_hit)


def quality_by_modality(rows: list[tuple[str, float, float]]) -> dict[str, float]:
    """Mean gap (own less other) by modality of (modality, own, other)."""
    return {m: statistics.fmean(a - b for x, a, b in rows if x == m) for m in sorted({x for x, _, _ in rows})}


def benchmark(fn: Callable[[], object], runs: int = 5) -> dict:
    times = []
    for _ in range(runs):
        began = time.perf_counter()
        fn()
        times.append(time.perf_counter() - began)
    return {"mean": statistics.fmean(times), "std": statistics.pstdev(times), "runs": runs}


def peak_rss() -> int:
    """Peak resident bytes of this process."""
    import resource

    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss * 1024 if os.name == "posix" else 0


def sweep_concurrency(run: Callable[[int], object], limits=(8, 16, 32, 64, 128)) -> dict[int, float]:
    return {c: benchmark(lambda c=c: run(c), 1)["mean"] for c in limits}
