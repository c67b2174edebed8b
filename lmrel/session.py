"""Calls, features, the runtime and the ledger."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame

from lmrel.functions.constraints import Constraint
from lmrel.functions.types import infer_return_type, parse_quantifier, parse_type
from lmrel.sources.providers import RuleProvider


@dataclass(frozen=True)
class LmCall:
    """A row-wise call: a question over one or more columns."""

    question: str
    columns: tuple[str, ...]
    return_type: str | None = None
    options: tuple[str, ...] | None = None
    quantifier: str | None = None
    modality: str = "text"
    examples: bool = True

    def typed(self, template: str) -> "LmCall":
        return self if self.return_type else replace(self, return_type=infer_return_type(template))

    @property
    def ddl(self) -> str:
        return parse_type(self.return_type or "str")

    @property
    def constraint(self) -> Constraint:
        if self.ddl.startswith("array"):
            return Constraint.list_of(self.ddl[6:-1], *parse_quantifier(self.quantifier), options=self.options)
        return Constraint.from_options(self.options, self.ddl) if self.options else Constraint.from_type(self.ddl)

    @property
    def fingerprint(self) -> str:
        return hashlib.sha256(repr((self.question, self.columns, self.ddl, self.options, self.quantifier)).encode()).hexdigest()[:16]


def lm_map(question: str, *columns: str, return_type: str | None = None, options=None, quantifier: str | None = None, modality: str = "text", examples: bool = True) -> LmCall:
    return LmCall(question, tuple(columns), return_type, tuple(options) if options else None, quantifier, modality, examples)


@dataclass(frozen=True)
class Features:
    """Early exit, cascade filter, constrained decoding, early dedup; one prompt per input or ``batch``."""

    ee: bool = True
    cf: bool = True
    cd: bool = True
    ed: bool = True
    pre: bool = True
    batch: int = 1


#: From the earlier release to everything on, one step at a time.
ABLATION_LADDER = [
    ("none", Features(False, False, False, False)), ("+ee", Features(True, False, False, False)), ("+ee+ed", Features(True, False, False, True)),
    ("+ee+ed+cd", Features(True, False, True, True)), ("+ee+ed+cd+cf", Features(True, True, True, True)),
]


class BudgetExceeded(RuntimeError):
    pass


@dataclass
class Runtime:
    """Provider, switches and what was spent.  Answers of a call site are kept and never asked again."""

    provider: object = field(default_factory=RuleProvider)
    features: Features = field(default_factory=Features)
    max_concurrency: int = 64
    retries: int = 2
    fail_fast: bool = True
    max_calls: int | None = None
    max_pairs: int = 10_000_000
    sampled: int = 0  # rows on which the calls of a cascade are tried to order them; 0: as written
    cache: object | None = None
    answers_in: str = "auto"  # how answers are kept, see materialise
    dry: bool = False
    answers: dict = field(default_factory=dict)
    ledger: list = field(default_factory=list)

    def record(self, call: object, **spent) -> None:
        self.ledger.append({"fn": getattr(call, "fingerprint", str(call)), "question": getattr(call, "question", str(call)), **spent})
        if self.max_calls is not None and self.calls > self.max_calls:
            raise BudgetExceeded(f"{self.calls} calls; the budget is {self.max_calls}")

    def total(self, what: str) -> int:
        return sum(row.get(what, 0) for row in self.ledger)

    @property
    def calls(self) -> int:
        return self.total("calls")

    def release(self) -> None:
        for df in self.answers.values():
            df.unpersist()
        self.answers.clear()


def materialise(df: DataFrame, mode: str = "cache") -> DataFrame:
    """A barrier before a second use.

    ``cache`` keeps rows on the executors' disks, so a lost executor's rows are computed again;
    ``checkpoint`` writes them to the session's checkpoint folder at once and cuts the lineage;
    ``auto`` is a checkpoint where the session has such a folder and else the cache; ``none`` is no
    barrier, for a single use.
    """
    from pyspark import StorageLevel

    if mode not in ("auto", "cache", "checkpoint", "none"):
        raise ValueError(f"unknown mode {mode}")
    if mode == "none":
        return df
    context = df.sparkSession.sparkContext
    unset = context._jsc.sc().getCheckpointDir().isEmpty()
    named = context.getConf().get("spark.checkpoint.dir")
    if unset and named and mode != "cache":
        context.setCheckpointDir(named)
    if mode == "checkpoint" and unset and not named:
        raise ValueError("the session names no checkpoint folder")
    if mode == "checkpoint" or mode == "auto" and named:
        return df.checkpoint()
    return df.persist(StorageLevel.DISK_ONLY)


def keep(df: DataFrame) -> DataFrame:
    """Rows that can be had again without a call, on the executors' disks."""
    return materialise(df, "cache")
