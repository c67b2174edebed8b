"""LmFrame: DataFrames with language-model conditions and columns, planned before they run."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lmrel.operators.executor import with_answers
from lmrel.plans.ir import And, Expr, LmAtom, Optimizer, Select, calls, has_or, is_cascadable, is_early_exitable, normal, order_predicates, relax, rendered
from lmrel.session import LmCall, Runtime, keep


def judged(df: DataFrame, e: Expr, rt: Runtime) -> DataFrame:
    """Rows of ``df`` for which ``e`` is true, after native parts were applied."""
    own, f = df.columns, rt.features
    e = normal(e)
    if f.pre and has_or(e) and calls(e):
        settled = F.expr(rendered(e, {}))
        yes = df.where(settled)
        return yes.unionByName(_asked(df.where(settled.isNull()), e, rt).select(*own))
    return _asked(df, e, rt).select(*own)


def _asked(df: DataFrame, e: Expr, rt: Runtime) -> DataFrame:
    names: dict[LmCall, str] = {}
    found = calls(e)
    if rt.features.cf and is_cascadable(e):
        atoms = [p for p in e.parts if isinstance(p, LmAtom) and not p.more]
        stats = sampled_stats(df, atoms, rt, rt.sampled) if rt.sampled and len(atoms) > 1 else None
        for part in order_predicates(list(e.parts), stats):
            for c in calls(part):
                if c not in names:
                    names[c] = f"__lm{len(names)}"
                    df = with_answers(df, c, names[c], rt)
            df = df.where(rendered(part, names))
        return df
    for c in found:
        names[c] = f"__lm{len(names)}"
        df = with_answers(df, c, names[c], rt)
    return df.where(rendered(e, names))


def filtered(df: DataFrame, e: Expr, rt: Runtime) -> DataFrame:
    """WHERE e: prefilter, the calls on what is left, then the whole condition on real answers."""
    if rt.features.pre and (cond := relax(e)):
        df = df.where(cond)
    return judged(df, e, rt)


#: Rows of a wave that are taken in order; larger waves are key ranges, bounded by a sample of so many keys.
TAKEN, KEYS = 10_000, 2_000


def next_wave(rest: DataFrame, key: str, size: int) -> tuple[DataFrame, int, object, bool]:
    """About the ``size`` first rows of ``rest`` by ``key``, kept: (rows, their number, the last key, whether none is left).

    Small waves are a top-k; large ones are a range of keys whose upper end comes from a hash-chosen
    sample of the keys, so no sort and no single task holds a wave.
    """
    if size <= TAKEN:
        wave = keep(rest.orderBy(key).limit(size))
        n, top = wave.agg(F.count(F.lit(1)), F.max(key)).first()
        return wave, n, top, n < size
    total = rest.count()
    keys = sorted(r[0] for r in rest.select(key).orderBy(F.xxhash64(key), key).limit(KEYS).collect())
    at = math.ceil(size * len(keys) / max(1, total))
    wave = keep(rest if at >= len(keys) else rest.where(F.col(key) <= F.lit(keys[at])))
    n, top = wave.agg(F.count(F.lit(1)), F.max(key)).first()
    return wave, n, top, at >= len(keys)


def early_exit(df: DataFrame, e: Expr, k: int, key: str, rt: Runtime, concurrency: int = 32) -> DataFrame:
    """The first k rows by ``key`` (unique, not null) for which ``e`` is true.

    Waves of rows in key order; a wave is as large as the hit rate so far makes it likely to end the
    search, and after some waves as large as all before, so a limit that is never reached costs a
    number of waves that grows with the logarithm of the rows.  Answers of earlier waves are not
    asked again.  The waste is below one wave.
    """
    if rt.features.pre and (cond := relax(e)):
        df = df.where(cond)
    if not rt.features.ee:
        return judged(df, e, rt).orderBy(key).limit(k)
    found, asked, last, hits, ended = 0, 0, None, [], False
    while found < k and not ended:
        share = (found + 1) / (asked + 2)
        size = math.ceil(1.2 * (k - found) / share) + concurrency
        size = max(size, asked) if len(hits) >= 6 else size
        wave, n, top, ended = next_wave(df if last is None else df.where(F.col(key) > F.lit(last)), key, size)
        if not n:
            wave.unpersist()
            break
        got = keep(judged(wave, e, rt))
        found, asked, last = found + got.count(), asked + n, top
        wave.unpersist()  # its hits are kept
        hits.append(got)
    out = hits[0] if hits else df.limit(0)
    for h in hits[1:]:
        out = out.unionByName(h)
    return out.orderBy(key).limit(k)


def first_rows(df: DataFrame, e: Expr, k: int, rt: Runtime, concurrency: int = 32) -> DataFrame:
    """Any k rows for which ``e`` is true, for a LIMIT without an order.

    The first rows that Spark finds are judged, then twice as many or more, up to ten times TAKEN,
    then all; what was answered before is not asked again.
    """
    if rt.features.pre and (cond := relax(e)):
        df = df.where(cond)
    size = k + concurrency
    while rt.features.ed and size <= 10 * TAKEN:
        part = keep(df.limit(size))
        n, got = part.count(), keep(judged(part, e, rt))
        found = got.count()
        part.unpersist()
        if found >= k or n < size:
            return got.limit(k)
        size = max(2 * size, math.ceil(1.2 * k * (n + 2) / (found + 1)))
    return judged(df, e, rt).limit(k)


def execute(df: DataFrame, s: Select, rt: Runtime, key: str | None = None) -> DataFrame:
    """A query block in the order that the optimizer plans: prefilter, calls of WHERE, limit, calls of SELECT.

    A limit that no other clause stands before ends the search early (in the order of ``key``, if
    given) and comes before the projection's calls, so only rows that are returned are asked about.
    """
    early = is_early_exitable(s)
    if s.where is not None:
        if early and rt.features.ee:
            df = early_exit(df, s.where, s.limit, key, rt) if key else first_rows(df, s.where, s.limit, rt)
        else:
            df = filtered(df, s.where, rt)
    if early:
        df = keep(df.orderBy(key).limit(s.limit) if key else df.limit(s.limit))
    for name, call in s.projections.items():
        df = with_answers(df, call, name, rt)
    return df


@dataclass
class LmFrame:
    """A frame with the runtime that answers its calls."""

    df: DataFrame
    rt: Runtime

    def where(self, e: Expr) -> "LmFrame":
        return LmFrame(filtered(self.df, e, self.rt), self.rt)

    def with_lm(self, name: str, call: LmCall) -> "LmFrame":
        return LmFrame(with_answers(self.df, call, name, self.rt), self.rt)

    def where_limit(self, e: Expr, k: int, key: str) -> "LmFrame":
        return LmFrame(early_exit(self.df, e, k, key, self.rt), self.rt)

    def execute(self, s: Select, key: str | None = None) -> "LmFrame":
        return LmFrame(execute(self.df, s, self.rt, key), self.rt)

    def explain_lm(self, s: Select) -> str:
        return "\n".join(f"{i}. {x.kind}: {x.detail}" for i, x in enumerate(Optimizer(self.rt.features).plan(s), 1))


# Thin wrappers over the two functions, by the names that other engines give them.
def lm_filter(df: DataFrame, question: str, *columns: str, rt: Runtime) -> DataFrame:
    return filtered(df, LmAtom(LmCall(question, columns, "bool")), rt)


def lm_classify(df: DataFrame, name: str, question: str, *columns: str, options, rt: Runtime) -> DataFrame:
    return with_answers(df, LmCall(question, columns, "str", tuple(options)), name, rt)


def lm_extract(df: DataFrame, name: str, question: str, *columns: str, struct: str, rt: Runtime) -> DataFrame:
    return with_answers(df, LmCall(question, columns, struct), name, rt)


def lm_score(df: DataFrame, name: str, question: str, *columns: str, rt: Runtime) -> DataFrame:
    return with_answers(df, LmCall(question, columns, "int"), name, rt)


def sampled_stats(df: DataFrame, atoms: list[LmAtom], rt: Runtime, rows: int = 200) -> dict:
    """(tokens, distinct inputs, selectivity) of each call on the rows of least hash."""
    part = keep(df.orderBy(F.xxhash64(*df.columns)).limit(rows))
    total, out = max(1, part.count()), {}
    for a in atoms:
        before = rt.total("in_tokens")
        hit = with_answers(part, a.call, "__s", rt).where(rendered(a, {a.call: "__s"})).count()
        inputs = part.select(*a.call.columns).distinct().count()
        out[a.call] = ((rt.total("in_tokens") - before) / max(1, inputs), inputs, hit / total)
    return out
