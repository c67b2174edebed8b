"""Asking the model: distinct inputs out, answers with their ledger fields back, joined to the rows."""

from __future__ import annotations

import json
import random
import time
from collections import deque
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lmrel.functions.constraints import ScoredToyModel, constrained_decode, parse_lenient
from lmrel.functions.prompts import SEPARATOR, render_batch_prompt, render_map_prompt
from lmrel.functions.types import parse_quantifier
from lmrel.session import LmCall, Runtime, keep, materialise
from lmrel.sources import media
from lmrel.sources.providers import Request
from lmrel.sources.tables import ANSWERS

#: Answers that a worker hands back at once.
FRAME = 1000


def canon(df: DataFrame, columns: tuple[str, ...]) -> Column:
    """The inputs of a call as JSON with explicit nulls; -0.0 counts as 0.0."""
    kinds = dict(df.dtypes)
    fixed = [(F.col(c) + F.lit(0.0)).alias(c) if kinds[c] in ("double", "float") else F.col(c) for c in columns]
    return F.to_json(F.struct(*fixed), {"ignoreNullFields": "false"})


def key_of(text: Column) -> Column:
    return F.substring(F.unhex(F.sha2(text, 256)), 1, 16)


def _worker(call: LmCall, rt: Runtime):
    """Rows (inputs as JSON) to answers in input order, at most ``max_concurrency`` requests in flight.

    The window of requests goes on over the Arrow batches of a task, so it holds at most that many
    inputs and FRAME answers, however many rows come.  Media are read by the thread that sends the
    request, so at most ``max_concurrency`` times a request's references are in memory.
    """
    provider, constraint, cd, b = rt.provider, call.constraint, rt.features.cd, rt.features.batch
    ddl, sizes, options, retries, fail_fast = call.ddl, parse_quantifier(call.quantifier), call.options, rt.retries, rt.fail_fast
    threads = 1 if getattr(provider, "name", "") in ("rule", "replay") and not getattr(provider, "service_s", 0) or not getattr(provider, "service_s", 1) else rt.max_concurrency

    def sent(request: Request) -> tuple | None:
        for attempt in range(retries + 1):
            try:
                files = media.loaded(request.batch or (request.inputs,))  # held until the reply only
                return provider.complete(replace(request, media=files) if files else request)
            except (FileNotFoundError, ValueError):  # the model cannot take this request, so again is no use
                if fail_fast:
                    raise
                return None
            except (OSError, TimeoutError):
                if attempt == retries:
                    if fail_fast:
                        raise
                    return None
                time.sleep(min(8.0, 0.2 * 2**attempt) * (0.5 + random.random()))

    def read(raw: str) -> tuple:
        valid = constraint.matches(raw)
        text = raw if valid else constrained_decode(ScoredToyModel(raw), constraint) if cd else parse_lenient(raw, constraint)
        if text is None or not constraint.matches(text):
            return None, "malformed", False
        return constraint.json(text), "ok", valid or cd

    def one(inputs: str) -> tuple:
        got = sent(Request(call.question, inputs, render_map_prompt(call.question, inputs, ddl, options, sizes, call.examples), constraint, call.modality))
        if got is None:
            return None, "error", 0, 0, False, 1
        value, status, valid = read(got[0])
        return value, status, got[1], got[2], valid, 1

    def some(group: list[str]) -> list[tuple]:
        """One request for several inputs; a reply with another number of values is asked again input by input."""
        if len(group) == 1:
            return [one(group[0])]
        prompt = render_batch_prompt(call.question, group, ddl, options, sizes, call.examples)
        got = sent(Request(call.question, json.dumps(group, ensure_ascii=False), prompt, constraint, call.modality, tuple(group)))
        parts = [p.strip() for p in got[0].split(SEPARATOR)] if got else []
        spent = (got[1], got[2]) if got else (0, 0)
        if len(parts) != len(group):
            out = [one(x) for x in group]
        else:
            out = [(value, status, 0, 0, valid, 0) for value, status, valid in map(read, parts)]
        value, status, tokens_in, tokens_out, valid, n = out[0]
        return [(value, status, tokens_in + spent[0], tokens_out + spent[1], valid, n + 1), *out[1:]]

    def frames(got: list[tuple]) -> pd.DataFrame:
        return pd.DataFrame(got, columns=["k", "value", "status", "in_tokens", "out_tokens", "valid", "calls"])

    def groups(batches: Iterator[pd.DataFrame]) -> Iterator[tuple[list, list]]:
        for frame in batches:
            keys, inputs = frame["k"].tolist(), frame["inputs"].tolist()
            yield from ((keys[i : i + b], inputs[i : i + b]) for i in range(0, len(keys), b))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        done: list[tuple] = []
        with ThreadPoolExecutor(threads) as pool:
            window: deque = deque()
            try:
                for keys, inputs in groups(batches):
                    window.append((keys, pool.submit(some, inputs) if threads > 1 else None, inputs))
                    while len(window) >= threads:
                        keys, future, inputs = window.popleft()
                        done += [(k, *x) for k, x in zip(keys, future.result() if future else some(inputs))]
                    if len(done) >= FRAME:
                        yield frames(done)
                        done = []
                for keys, future, inputs in window:
                    done += [(k, *x) for k, x in zip(keys, future.result() if future else some(inputs))]
            except GeneratorExit:  # the task was cancelled: requests that did not begin are not sent
                pool.shutdown(wait=False, cancel_futures=True)
                raise
        if done:
            yield frames(done)

    return run


def ask_rows(inputs: DataFrame, call: LmCall, rt: Runtime) -> DataFrame:
    """Answers of (k, inputs), kept, with the requests that were made recorded in the ledger."""
    if rt.dry:
        n = inputs.count()
        rt.record(call, calls=-(-n // rt.features.batch), inputs=n, in_tokens=0, out_tokens=0, malformed=0)
        return inputs.select("k", *(F.lit(None).cast(t).alias(c) for c, t in (x.split() for x in ANSWERS.split(", ")[1:])))
    if rt.answers_in == "none":
        raise ValueError("answers are used more than once, so they have to be kept")
    got = materialise(inputs.mapInPandas(_worker(call, rt), ANSWERS), rt.answers_in)
    spent = got.agg(F.count(F.lit(1)), F.sum("in_tokens"), F.sum("out_tokens"), F.sum((~F.col("valid")).cast("int")), F.sum("calls")).first()
    rt.record(call, calls=spent[4] or 0, inputs=spent[0], in_tokens=spent[1] or 0, out_tokens=spent[2] or 0, malformed=spent[3] or 0, modality=call.modality)
    if rt.cache is not None:
        rt.cache.append(call.fingerprint, got)
    return got


def typed(value: Column, ddl: str) -> Column:
    field = f"v {ddl}" if not ddl.startswith(("date", "timestamp")) else "v string"
    out = F.from_json(F.concat(F.lit('{"v":'), value, F.lit("}")), field)["v"]
    return out.cast(ddl) if ddl.startswith(("date", "timestamp")) else out


def with_answers(df: DataFrame, call: LmCall, name: str, rt: Runtime) -> DataFrame:
    """``df`` with the call's answers in column ``name``.

    With early dedup only distinct inputs without an answer so far are asked: inputs are keyed by 16
    bytes first, so the shuffle is by key, and answers come back by a join on it.  Rows whose inputs
    are all null are not asked and get null; in that join each has a key of 8 bytes of its own, which
    meets nothing, so they are dealt evenly.
    """
    if name in df.columns:
        raise ValueError(f"column {name} exists already")
    text, some = canon(df, call.columns), F.coalesce(*(F.col(c).cast("string") if t != "binary" else F.hex(c) for c, t in df.dtypes if c in call.columns)).isNotNull()
    if not rt.features.ed:
        full = df.withColumn("__row", F.when(some, F.monotonically_increasing_id()))
        full = keep(full.withColumn("__k", F.unhex(F.lpad(F.hex("__row"), 16, "0"))))
        got = ask_rows(full.where("__k IS NOT NULL").select(F.col("__k").alias("k"), text.alias("inputs")), call, rt)
        return full.join(got.select(F.col("k").alias("__k"), typed(F.col("value"), call.ddl).alias(name)), "__k", "left").drop("__k", "__row")
    site = f"{call.fingerprint}-{rt.features.cd}"
    known = rt.answers.get(site)
    if known is None and rt.cache is not None:
        known = rt.cache.read(call.fingerprint)
    todo = df.where(some).select(key_of(text).alias("k"), text.alias("inputs")).dropDuplicates(["k"])
    got = ask_rows(todo if known is None else todo.join(known.select("k"), "k", "left_anti"), call, rt)
    known = got if known is None else known.select(*got.columns).unionByName(got)
    rt.answers[site] = known
    answers = known.select(F.col("k").alias("__k"), typed(F.col("value"), call.ddl).alias(name))
    alone = F.unhex(F.lpad(F.hex(F.xxhash64(F.spark_partition_id(), F.monotonically_increasing_id())), 16, "0"))
    return df.withColumn("__k", F.when(some, key_of(text)).otherwise(alone)).join(answers, "__k", "left").drop("__k")
