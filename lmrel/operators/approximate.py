"""Budgeted aggregates with certain bounds, and a cascade of a cheap proxy before the main model."""

from __future__ import annotations

import math
from itertools import groupby

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lmrel.operators.executor import with_answers
from lmrel.operators.frame import next_wave
from lmrel.plans.ir import LmAtom, rendered
from lmrel.session import LmCall, Runtime, keep


def aqp_aggregate(df: DataFrame, atom: LmAtom, agg: str, key: str, rt: Runtime, column: str | None = None, max_calls: int | None = None, max_error: float = 0.0, wave: int = 256) -> dict:
    """lower, upper, estimate and asked of count, sum, min, max or avg over the rows for which atom holds.

    Rows are asked in key order, in waves that double, until the bounds are ``max_error`` apart,
    ``max_calls`` rows were asked or none is left.  Rows not asked count as both outcomes, so bounds
    are certain.  The native sums are taken once and reduced by what each wave has asked.
    """
    if agg not in ("count", "sum", "min", "max", "avg"):
        raise ValueError(agg)
    x = F.col(column) if column else F.lit(1)
    sums = [F.count(F.lit(1)).alias("n"), F.sum(F.when(x < 0, x).otherwise(0)).alias("neg"), F.sum(F.when(x > 0, x).otherwise(0)).alias("pos")]
    left = df.agg(*sums).first().asDict()
    total, asked, last, yes = left["n"], 0, None, {"n": 0, "s": 0, "lo": None, "hi": None}
    while True:
        size = min(wave, total - asked, (max_calls if max_calls is not None else total) - asked)
        rest = df if last is None else df.where(F.col(key) > F.lit(last))
        if size > 0:
            part, n, last, _ = next_wave(rest, key, size)
            hit = F.coalesce(F.expr(rendered(atom, {atom.call: "__a"})), F.lit(False))
            got = with_answers(part, atom.call, "__a", rt).withColumn("__t", hit)
            own = got.agg(F.sum(F.col("__t").cast("int")).alias("hits"), F.sum(F.when(F.col("__t"), x)).alias("s"), F.min(F.when(F.col("__t"), x)).alias("lo"), F.max(F.when(F.col("__t"), x)).alias("hi"), *sums[1:]).first()
            part.unpersist()
            asked, wave = asked + n, 2 * wave
            yes = {"n": yes["n"] + (own.hits or 0), "s": yes["s"] + (own.s or 0), "lo": _least(yes["lo"], own.lo), "hi": _most(yes["hi"], own.hi)}
            left = {"n": total - asked, "neg": (left["neg"] or 0) - (own.neg or 0), "pos": (left["pos"] or 0) - (own.pos or 0)}
            rest = df.where(F.col(key) > F.lit(last))
        state = _bounds(yes, left, rest, x, agg, asked) | {"asked": asked}
        if size <= 0 or asked >= total or (state["lower"] is not None and state["upper"] is not None and state["upper"] - state["lower"] <= max_error):
            return state


def _least(*v):
    return min((i for i in v if i is not None), default=None)


def _most(*v):
    return max((i for i in v if i is not None), default=None)


def _bounds(yes: dict, left: dict, rest: DataFrame, x: Column, agg: str, asked: int) -> dict:
    n, s, share = yes["n"], yes["s"], yes["n"] / asked if asked else 0.5
    if agg == "count":
        return {"lower": n, "upper": n + left["n"], "estimate": n + share * left["n"]}
    if agg == "sum":
        neg, pos = left["neg"] or 0, left["pos"] or 0
        return {"lower": s + neg, "upper": s + pos, "estimate": s + share * (neg + pos)}
    if agg == "max":
        return {"lower": yes["hi"], "upper": _most(yes["hi"], rest.agg(F.max(x)).first()[0]), "estimate": yes["hi"]}
    if agg == "min":
        return {"lower": _least(yes["lo"], rest.agg(F.min(x)).first()[0]), "upper": yes["lo"], "estimate": yes["lo"]}
    ends = [_extreme(rest, x, s, n, up) for up in (False, True)]
    return {"lower": ends[0], "upper": ends[1], "estimate": s / n if n else None}


def _extreme(rest: DataFrame, x: Column, s: float, n: int, up: bool) -> float | None:
    """The mean pushed furthest by adding unasked values: those beyond the mean that they give.

    From the mean so far, the values beyond it are added, which moves the mean on, until no value
    lies between; every step is one aggregate, and the steps are few, as the mean jumps.
    """
    own = x.cast("double")
    if not n:
        return rest.agg((F.max if up else F.min)(own)).first()[0]
    mean = s / n
    for _ in range(100):
        t = rest.where(own > F.lit(mean) if up else own < F.lit(mean)).agg(F.count(own), F.sum(own)).first()
        after = (s + (t[1] or 0.0)) / (n + t[0])
        if after == mean or (after < mean) == up:
            break
        mean = after
    return mean


def wilson(hits: int, n: int, z: float = 1.96) -> tuple[float, float]:
    if not n:
        return 0.0, 1.0
    p, d = hits / n, 1 + z * z / n
    mid, half = (p + z * z / (2 * n)) / d, z * math.sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / d
    return mid - half, mid + half


def cut_offs(known: list[tuple[float, bool]], target_precision: float, target_recall: float) -> dict:
    """Scores from which rows are taken (``high``) and below which they are left (``low``), from judged (score, answer).

    Cuts lie between different scores only.  ``high`` is the least score at and above which the lower
    bound of the precision reaches its target (none: above all scores); ``low`` the greatest at and
    above which the lower bound of the recall does (none: 0, so nothing is left unasked).
    """
    out = {"high": math.inf, "low": 0.0, "sampled": len(known), "precision_bounds": (0.0, 1.0), "recall_bounds": (0.0, 1.0)}
    positives, n, hits, lowest = sum(y for _, y in known), 0, 0, None
    for score, rows in groupby(sorted(known, key=lambda r: -r[0]), key=lambda r: r[0]):
        rows = list(rows)
        n, hits = n + len(rows), hits + sum(y for _, y in rows)
        if wilson(hits, n)[0] >= target_precision:
            out |= {"high": score, "precision_bounds": wilson(hits, n)}
        if lowest is None and positives and wilson(hits, positives)[0] >= target_recall:
            lowest = score
            out |= {"low": score, "recall_bounds": wilson(hits, positives)}
    return out


def proxy_cascade(df: DataFrame, main: LmCall, proxy, rt: Runtime, target_precision: float = 0.9, target_recall: float = 0.9, sample: int = 200, by: Column | None = None) -> tuple[DataFrame, dict]:
    """Rows that the cascade accepts, and its cut-offs.  ``proxy`` is a score column of 0 or more.

    The main model judges ``sample`` rows, chosen by the hash of the whole row (or the order ``by``),
    so that copies of one text do not fill the sample.  Rows that score ``high`` or more are taken
    unasked, rows under ``low`` are left, in between the main model is asked.  A row whose score is
    null is asked.  Lossy, so never used unless called for.
    """
    own = df.columns
    scored = df.withColumn("__p", proxy)
    part = with_answers(scored.where("__p IS NOT NULL").orderBy(by if by is not None else F.xxhash64(*own), *main.columns).limit(sample), main, "__a", rt).select("__p", "__a").collect()
    cut = cut_offs([(float(r["__p"]), bool(r["__a"])) for r in part], target_precision, target_recall)
    yes = scored.where(F.col("__p") >= F.lit(cut["high"]))
    between = scored.where(F.col("__p").isNull() | (F.col("__p") < F.lit(cut["high"])) & (F.col("__p") >= F.lit(cut["low"])))
    asked = with_answers(keep(between), main, "__a", rt).where("__a")
    return yes.select(*own).unionByName(asked.select(*own)), cut
