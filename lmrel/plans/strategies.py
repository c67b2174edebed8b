"""The ways of other engines re-created as switches of ours, each with its ledger."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from lmrel.operators.frame import early_exit, filtered
from lmrel.plans.ir import And, Expr, Native, calls, is_early_exitable, normal, Select
from lmrel.session import ABLATION_LADDER, Features, LmCall, Runtime, keep
from lmrel.operators.executor import with_answers
from lmrel.plans.ir import rendered

STRATEGIES = {
    "ours": Features(),
    "eager": Features(ee=False, cf=False, cd=False, ed=False, pre=False),
    "lazy": Features(ee=True, cf=True, cd=False, ed=False),
    "aqp": Features(ee=True, cf=False, cd=False, ed=False),
    "v0": Features(ee=False, cf=False, cd=False, ed=False, batch=5),
    "naive_udf": Features(ee=False, cf=False, cd=False, ed=False, pre=False),
} | {name: f for name, f in ABLATION_LADDER}
#: What a strategy cannot run, by the capabilities that a query needs.
MISSING = {"ours": set(), "eager": {"audio"}, "lazy": {"rerank"}, "aqp": {"lm_aggregation", "projection"}, "v0": set(), "naive_udf": {"lm_aggregation"}}


def covered(strategy: str, needs: set[str]) -> bool:
    return not (MISSING.get(strategy, set()) & needs)


@dataclass
class Workload:
    """A filter query with an optional limit, in the order in which a user wrote its predicates."""

    df: DataFrame
    where: Expr
    key: str
    limit: int | None = None


def eager(w: Workload, rt: Runtime) -> DataFrame:
    """Every predicate in written order over all rows that are left, materialised before the next."""
    out = w.df
    parts = normal(w.where).parts if isinstance(normal(w.where), And) else (w.where,)
    for i, p in enumerate(parts):
        if isinstance(p, Native):
            out = keep(out.where(p.sql))
            continue
        names: dict[LmCall, str] = {}
        for c in calls(p):
            names[c] = f"__e{i}_{len(names)}"
            out = with_answers(out, c, names[c], rt)
        out = keep(out.where(rendered(p, names)).select(*w.df.columns))
    return out.orderBy(w.key).limit(w.limit) if w.limit is not None else out


def run(w: Workload, strategy: str, provider=None) -> tuple[DataFrame, Runtime]:
    rt = Runtime(features=STRATEGIES[strategy], **({"provider": provider} if provider else {}))
    if strategy in ("eager", "naive_udf"):
        return eager(w, rt), rt
    if w.limit is not None and is_early_exitable(Select(w.where, limit=w.limit)):
        return early_exit(w.df, w.where, w.limit, w.key, rt), rt
    out = filtered(w.df, w.where, rt)
    return (out.orderBy(w.key).limit(w.limit) if w.limit is not None else out), rt


def ablate(w: Workload, provider=None) -> list[dict]:
    """Calls, malformed replies and rows for every step of the ladder."""
    out = []
    for name, _ in ABLATION_LADDER:
        df, rt = run(w, name, provider)
        rows = df.count()
        out.append({"step": name, "rows": rows, "calls": rt.calls, "malformed": rt.total("malformed")})
        rt.release()
    return out
