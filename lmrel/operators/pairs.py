"""Joins judged by the model: pairs of distinct inputs, streamed to the workers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lmrel.operators.executor import with_answers
from lmrel.session import LmCall, Runtime, keep


class TooManyPairs(ValueError):
    pass


def lm_join(left: DataFrame, right: DataFrame, question: str, lcols: tuple[str, ...], rcols: tuple[str, ...], rt: Runtime, on: str | None = None, how: str = "inner") -> DataFrame:
    """Rows of both sides for which the model says yes; ``how`` inner, left_semi or left_anti.

    Where no native condition is given, pairs are made of the distinct inputs of either side only,
    judged, and the yes-pairs joined back by equality; the product of the sides' distinct inputs
    must be under the runtime's ``max_pairs``.  With ``on`` (native SQL over both sides) the pairs
    that it leaves are judged, one call per distinct pair.
    """
    if set(left.columns) & set(right.columns):
        raise ValueError("the sides share column names")
    call = LmCall(question, (*lcols, *rcols), "bool")
    if on is None and rt.features.ed:
        a, b = keep(left.select(*lcols).distinct()), keep(right.select(*rcols).distinct())
        if (n := a.count() * b.count()) > rt.max_pairs:
            raise TooManyPairs(f"{n} pairs; give a native condition or raise max_pairs above {rt.max_pairs}")
        yes = with_answers(a.crossJoin(b), call, "__yes", rt).where("__yes").select(*(F.col(c).alias(f"__{c}") for c in (*lcols, *rcols)))
        match = lambda df, cols: [df[c].eqNullSafe(yes[f"__{c}"]) for c in cols]
        test = match(left, lcols)
        for_left = test[0]
        for t in test[1:]:
            for_left = for_left & t
        if how != "inner":
            return left.join(yes, for_left, how)
        out = left.join(yes, for_left)
        other = match(right, rcols)
        cond = other[0]
        for t in other[1:]:
            cond = cond & t
        return out.join(right, cond).select(*left.columns, *right.columns)
    pairs = left.crossJoin(right) if on is None else left.join(right, F.expr(on))
    yes = with_answers(pairs, call, "__yes", rt).where("__yes").drop("__yes")
    if how == "inner":
        return yes
    keys = yes.select(*(F.col(c).alias(f"__{c}") for c in left.columns)).distinct()
    test = left[left.columns[0]].eqNullSafe(keys[f"__{left.columns[0]}"])
    for c in left.columns[1:]:
        test = test & left[c].eqNullSafe(keys[f"__{c}"])
    return left.join(keys, test, how)
