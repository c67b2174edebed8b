"""Set functions: one answer for a whole relation, top-k choice, linking, retrieval, one answer per group."""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lmrel.functions.constraints import NONE, Constraint, ScoredToyModel, constrained_decode, parse_lenient
from lmrel.functions.prompts import approx_tokens, render_ask_prompt
from lmrel.functions.skills import BY_QUESTION
from lmrel.functions.types import parse_quantifier, parse_type
from lmrel.session import Runtime, keep
from lmrel.sources.providers import Request, said

MAX_ROWS, MAX_CHARS = 5_000, 120_000


class ContextTooLarge(ValueError):
    pass


def collect_context(df: DataFrame, max_rows: int = MAX_ROWS, max_chars: int = MAX_CHARS) -> list[dict]:
    """The rows in the order of their values; refuses what does not fit one prompt."""
    rows = [r.asDict() for r in df.orderBy(*df.columns).limit(max_rows + 1).collect()]
    if len(rows) > max_rows or len(json.dumps(rows, default=str)) > max_chars:
        raise ContextTooLarge(f"more than {max_rows} rows or {max_chars} characters; reduce='tree' asks in parts")
    return rows


def _answer(question: str, inputs: object, constraint: Constraint, prompt: str, rt: Runtime):
    raw, tokens_in, tokens_out = rt.provider.complete(Request(question, json.dumps({"rows": inputs}, default=str, ensure_ascii=False), prompt, constraint))
    ok = constraint.matches(raw)
    text = raw if ok else constrained_decode(ScoredToyModel(raw), constraint) if rt.features.cd else parse_lenient(raw, constraint)
    rt.record(question, calls=1, inputs=1, in_tokens=tokens_in, out_tokens=tokens_out, malformed=0 if ok or rt.features.cd else 1)
    return None if text is None else json.loads(constraint.json(text))


class _Ranked:
    """The rule reasoner's way with sets: a rule sorts the options, the answer is the first or the first k."""

    def __init__(self, inner, k: int | None):
        self.inner, self.k, self.name = inner, k, getattr(inner, "name", "rule")

    def complete(self, r: Request):
        skill = BY_QUESTION.get(r.question)
        if skill is None or not hasattr(self.inner, "answer"):
            return self.inner.complete(r)
        best = skill.rule(json.loads(r.inputs)["rows"])
        raw = said(best[: self.k] if self.k is not None else best[0] if best else None, "array" if self.k is not None else "string")
        return raw, approx_tokens(r.prompt), approx_tokens(raw)


def lm_ask(question: str, rt: Runtime, context: DataFrame | None = None, options: DataFrame | list | None = None, return_type: str = "str", quantifier: str | None = None, reduce: str = "single", chunk: int = 1000):
    """One call for one cell: a Python value, to be used as a literal in the plan.

    ``options`` (distinct values) or ``context`` (rows) may be DataFrames; no rows give None or an
    empty list without a call.  ``reduce='tree'`` asks chunks of rows first, then their answers.
    """
    ddl = parse_type(return_type)
    least, most = parse_quantifier(quantifier)
    is_list = ddl.startswith("array")
    if isinstance(options, DataFrame):
        column = options.columns[0]
        values = options.select(F.col(column).cast("string").alias(column)).where(F.col(column).isNotNull()).distinct()
        if reduce == "tree":
            return _tree(question, rt, values, column, ddl, quantifier, chunk)
        options = [r[column] for r in collect_context(values)]
    rows = collect_context(context) if context is not None else None
    if (options is not None and not options) or (rows is not None and not rows):
        return [] if is_list else None
    if is_list and options is not None:
        least, most = min(least, len(options)), most if most is None else min(most, len(options))
    constraint = Constraint.list_of(ddl[6:-1], least, most, options) if is_list else Constraint.from_options(options, ddl) if options else Constraint.from_type(ddl)
    prompt = render_ask_prompt(question, json.dumps(rows, default=str) if rows is not None else None, ddl, options, (least, most) if is_list else None)
    inputs = options if options is not None else [r[next(iter(r))] if len(r) == 1 else r for r in rows] if rows is not None else []
    asked = Runtime(_Ranked(rt.provider, most if is_list else None), rt.features)
    out = _answer(question, inputs, constraint, prompt, asked)
    for row in asked.ledger:
        rt.record(row.pop("question"), **{k: v for k, v in row.items() if k != "fn"})
    return out


def _tree(question: str, rt: Runtime, values: DataFrame, column: str, ddl: str, quantifier: str | None, chunk: int):
    """Parts by hash, each answered in its task; their answers are the options of the next level.

    A part holds four times as many values as it gives back at least, so a level has a quarter of the
    values of the one before, or the parts are as small as the window asks for.  The last level is
    one prompt, also where a level did not shrink by a quarter; if that does not fit, it is refused.
    """
    level, last, k = values, None, parse_quantifier(quantifier)[1] or 1
    chunk = max(chunk, 4 * k)
    while True:
        n, size = level.agg(F.count(F.lit(1)), F.sum(F.octet_length(column))).first()
        stuck = last is not None and 4 * n > 3 * last
        if n <= chunk or stuck:
            try:
                return lm_ask(question, rt, options=level, return_type="list[str]" if ddl.startswith("array") else "str", quantifier=quantifier)
            except ContextTooLarge:
                if stuck:
                    raise
        last, parts = n, max(-(-n // chunk), 2 * -(-size // MAX_CHARS))
        provider, constraint_of = _Ranked(rt.provider, k), Constraint.list_of

        def run(frame: pd.DataFrame) -> pd.DataFrame:
            own = sorted(frame[column])
            request = Request(question, json.dumps({"rows": own}, ensure_ascii=False), render_ask_prompt(question, None, "array<string>", own, (k, k)), constraint_of("string", 0, k, own))
            raw, tokens_in, tokens_out = provider.complete(request)
            best, bad = _listed(raw, set(own), k)
            rows = best or [None]
            return pd.DataFrame({column: rows, "__in": [tokens_in] + [0] * (len(rows) - 1), "__out": [tokens_out] + [0] * (len(rows) - 1), "__calls": [1] + [0] * (len(rows) - 1), "__bad": [bad] + [0] * (len(rows) - 1)})

        dealt = level.withColumn("__p", F.pmod(F.xxhash64(column), F.lit(parts)))
        asked = keep(dealt.groupBy("__p").applyInPandas(run, f"{column} string, __in long, __out long, __calls long, __bad long"))
        spent = asked.agg(*(F.sum(c) for c in ("__calls", "__in", "__out", "__bad"))).first()
        rt.record(question, calls=spent[0] or 0, inputs=n, in_tokens=spent[1] or 0, out_tokens=spent[2] or 0, malformed=spent[3] or 0)
        level = asked.where(F.col(column).isNotNull()).select(column).distinct()


def _listed(raw: str, allowed: set[str], k: int) -> tuple[list[str], int]:
    """The allowed values of a list reply, k at most, each once; 1 with them if the reply held anything else."""
    try:
        said_values = json.loads(raw)
    except ValueError:
        return [], 1
    values = list(dict.fromkeys(v for v in said_values if isinstance(v, str) and v in allowed)) if isinstance(said_values, list) else []
    return values[:k], int(not isinstance(said_values, list) or values[:k] != said_values)


def _asked(question: str, rt: Runtime, options: DataFrame, **more):
    """One prompt, or a tree of parts where the options do not fit one."""
    try:
        return lm_ask(question, rt, options=options, **more)
    except ContextTooLarge:
        return lm_ask(question, rt, options=options, reduce="tree", **more)


def lm_topk(df: DataFrame, question: str, column: str, k: int, rt: Runtime) -> DataFrame:
    """(rank, column): the k best of a column's distinct values, by one call or, of many, by a tree of calls."""
    best = _asked(question, rt, df.select(column), return_type="list[str]", quantifier=f"{{{k}}}") or []
    return df.sparkSession.createDataFrame([(i + 1, v) for i, v in enumerate(best)], f"rank int, {column} string")


def lm_link(df: DataFrame, question: str, column: str, rt: Runtime, context: DataFrame) -> DataFrame:
    """Rows whose column equals the answer over the context; the literal reaches the scan as a filter."""
    answer = _asked(question, rt, context)
    return df.where(F.col(column) == F.lit(answer)) if answer is not None else df.limit(0)


def retrieve(df: DataFrame, vector: str, query: list[float], k: int, key: str) -> DataFrame:
    """The k rows of highest inner product with the query vector, ties by key."""
    q = F.array(*map(F.lit, query))
    score = F.aggregate(F.zip_with(F.col(vector).cast("array<double>"), q, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return df.withColumn("score", score).orderBy(F.desc("score"), key).limit(k)


def lm_agg(df: DataFrame, question: str, column: str, by: list[str], name: str, rt: Runtime, most: int = 256) -> DataFrame:
    """One answer per group over its distinct values, each of them one of the values.

    A group of more than ``most`` values is asked in chunks, dealt by hash, and the chunks' answers
    again, level by level, so no prompt and no task holds more than about a chunk of a group.  An
    answer that is none of the values counts as malformed and gives way to the first value.
    """
    level = df.select(*by, F.col(column).cast("string").alias("__v")).where("__v IS NOT NULL").distinct()
    provider, schema = rt.provider, level.schema
    full = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema) + ", __in long, __out long, __bad long"

    # Providers read the options only; an automaton of whole texts takes most of the time.
    def run(frame: pd.DataFrame) -> pd.DataFrame:
        own = sorted(frame["__v"])
        request = Request(question, json.dumps({"rows": own}, ensure_ascii=False), render_ask_prompt(question, None, "string", own), Constraint(NONE, "string", tuple(own)))
        raw, tokens_in, tokens_out = _Ranked(provider, None).complete(request)
        good = raw in set(own)
        return frame.iloc[:1].assign(__v=raw if good else own[0], __in=tokens_in, __out=tokens_out, __bad=int(not good))

    for depth in range(64):
        sizes = keep(level.groupBy(*by).agg(F.ceil(F.count(F.lit(1)) / most).alias("__n")))
        parts, groups = sizes.agg(F.max("__n"), F.sum("__n")).first()
        if rt.dry or parts is None:
            rt.record(question, calls=groups or 0, inputs=0, in_tokens=0, out_tokens=0, malformed=0)
            return level.limit(0).withColumnRenamed("__v", name)
        right = sizes.select(*(F.col(c).alias(f"__g{i}") for i, c in enumerate(by)), "__n")
        same = F.col("__v").isNotNull()
        for i, c in enumerate(by):
            same = same & F.col(c).eqNullSafe(F.col(f"__g{i}"))
        dealt = level.join(right, same).select(*level.columns, F.pmod(F.xxhash64(F.lit(depth), "__v"), F.col("__n")).alias("__c"))
        asked = keep(dealt.groupBy(*by, "__c").applyInPandas(lambda f: run(f.drop(columns="__c")), full))
        spent = asked.agg(F.count(F.lit(1)), *(F.sum(c) for c in ("__in", "__out", "__bad"))).first()
        rt.record(question, calls=spent[0], inputs=spent[0], in_tokens=spent[1] or 0, out_tokens=spent[2] or 0, malformed=spent[3] or 0)
        sizes.unpersist()
        level = asked.select(*schema.names)
        if parts == 1:
            return level.withColumnRenamed("__v", name)
    raise RuntimeError("the groups did not shrink")
