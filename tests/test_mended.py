"""Requests that are counted, cuts that hold, waves that end, groups that shrink."""

import json
import threading
import time
from dataclasses import dataclass

import pytest
from pyspark.sql import functions as F

from lmrel.functions.constraints import Constraint, ScoredToyModel, constrained_decode
from lmrel.operators import frame
from lmrel.operators.approximate import aqp_aggregate, cut_offs, proxy_cascade
from lmrel.operators.ask import lm_agg, lm_ask
from lmrel.operators.executor import _worker, with_answers
from lmrel.operators.frame import LmFrame, early_exit, filtered, first_rows
from lmrel.plans.ir import And, LmAtom, Select
from lmrel.session import Features, Runtime, lm_map
from lmrel.sources.providers import ReplayProvider, Request, RuleProvider

RED, RING = lm_map("Is it red?", "name", return_type="bool"), lm_map("Is it a ring?", "name", return_type="bool")


@pytest.fixture(scope="module")
def things(spark):
    return spark.range(600).selectExpr("id", "concat(IF(id % 7 = 0, 'red', 'blue'), IF(id % 2 = 0, ' ring', ' cog'), ' ', CAST(id AS STRING)) AS name", "CAST(id % 50 AS DOUBLE) AS x").cache()


def test_a_prompt_for_several_rows_is_one_request(things):
    @dataclass
    class Forgetful(RuleProvider):
        """Leaves out a value where a prompt for several holds a red thing."""

        name: str = "forgetful"

        def complete(self, r: Request):
            raw, a, b = super().complete(r)
            return (raw.split(";", 1)[1] if r.batch and "red" in r.inputs else raw), a, b

    few = things.where("id < 20").coalesce(1)
    single, batched = Runtime(), Runtime(features=Features(batch=5))
    want = {r.id for r in filtered(few, LmAtom(RED), single).collect()}
    assert {r.id for r in filtered(few, LmAtom(RED), batched).collect()} == want == {0, 7, 14}
    assert (single.calls, batched.calls) == (20, 4) and batched.total("in_tokens") < single.total("in_tokens")
    odd = Runtime(provider=Forgetful(), features=Features(batch=5))
    assert {r.id for r in filtered(few, LmAtom(RED), odd).collect()} == want
    assert 4 < odd.calls <= 4 + 20  # replies with too few values are asked again one by one


def test_few_requests_are_held_at_once():
    seen, lock, most, live = [], threading.Lock(), [0], [0]

    @dataclass
    class Slow(RuleProvider):
        name: str = "slow"
        service_s: float = 0.001

        def complete(self, r):
            with lock:
                live[0] += 1
                most[0] = max(most[0], live[0])
            time.sleep(0.002)
            with lock:
                live[0] -= 1
            return super().complete(r)

    import pandas as pd

    def batches():
        for i in range(80):
            seen.append(i)
            yield pd.DataFrame({"k": [b"%d" % (25 * i + j) for j in range(25)], "inputs": [json.dumps({"name": f"red {i} {j}"}) for j in range(25)]})

    got = _worker(RED, Runtime(provider=Slow(), max_concurrency=8))(batches())
    first = next(got)
    assert len(first) == 1000 and len(seen) <= 42  # read on as answers come, not ahead
    rest = [len(f) for f in got]
    assert len(first) + sum(rest) == 2000 and 1 < most[0] <= 8


def test_a_request_that_cannot_be_taken(things):
    @dataclass
    class Short(RuleProvider):
        name: str = "rule"

        def complete(self, r):
            if "red" in r.inputs:
                raise ValueError("too long")
            return super().complete(r)

    few = things.where("id < 20")
    got = with_answers(few, RED, "a", Runtime(provider=Short(), fail_fast=False))
    assert got.where("a IS NULL").count() == 3 and got.where("NOT a").count() == 17


def test_rows_without_inputs_are_spread(spark):
    rows = spark.range(4000).selectExpr("id", "IF(id < 3000, NULL, concat('red ', id % 3)) AS name")
    rt = Runtime()
    got = with_answers(rows, RED, "a", rt)
    assert rt.calls == 3 and got.count() == 4000 and got.where("a").count() == 1000 and got.where("a IS NULL").count() == 3000
    assert got.withColumn("p", F.spark_partition_id()).groupBy("p").count().agg(F.max("count")).first()[0] < 4000


def test_cut_offs_lie_between_scores():
    tied = [(0.5, i % 2 == 0) for i in range(200)]
    assert cut_offs(tied, 0.9, 0.9)["high"] == float("inf") and cut_offs(tied, 0.9, 0.9)["low"] == 0.5
    good = [(0.9, True)] * 80 + [(0.5, True)] * 10 + [(0.5, False)] * 10 + [(0.1, False)] * 100
    cut = cut_offs(good, 0.9, 0.9)
    assert cut["high"] == 0.9 and cut["low"] == 0.5 and cut["precision_bounds"][0] >= 0.9 and cut["recall_bounds"][0] >= 0.9
    assert cut_offs([], 0.9, 0.9)["low"] == 0.0


def test_proxy_cascade_keeps_its_targets(spark):
    # one score for all, half true: nothing may be taken unasked; copies of one text do not fill the sample
    rows = spark.range(1000).selectExpr("id", "concat(IF(id % 2 = 0, 'red', 'blue'), ' ', IF(id < 600, 0, id)) AS name")
    rt = Runtime()
    out, cut = proxy_cascade(rows, RED, F.lit(0.5), rt)
    assert out.count() == 500 == out.where("name LIKE 'red%'").count() and rt.calls == rows.select("name").distinct().count()
    noisy = F.when(F.col("name").like("red%"), 0.95).when(F.col("id") % 10 == 1, 0.5).otherwise(0.05)
    rt = Runtime()
    out, cut = proxy_cascade(rows, RED, noisy, rt)
    kept = {r.id for r in out.collect()}
    truth = set(range(0, 1000, 2))
    assert len(kept & truth) >= 0.9 * len(truth) and len(kept & truth) >= 0.9 * len(kept) and rt.calls < 402
    assert cut["precision_bounds"][0] >= 0.9


@pytest.mark.parametrize("taken", [frame.TAKEN, 40])
def test_waves_end(things, monkeypatch, taken):
    monkeypatch.setattr(frame, "TAKEN", taken)
    monkeypatch.setattr(frame, "KEYS", 100)
    e = And(LmAtom(RED), LmAtom(RING))
    for k in (3, 40, 1000):
        want = [i for i in range(0, 600, 14)][:k]
        assert [r.id for r in early_exit(things, e, k, "id", Runtime(), concurrency=4).collect()] == want
        got = {r.id for r in first_rows(things, e, k, Runtime(), concurrency=4).collect()}
        assert len(got) == min(k, 43) and got <= set(range(0, 600, 14))
    values = [i % 50 for i in range(0, 600, 7)]
    for agg, value in {"count": len(values), "sum": sum(values), "min": min(values), "max": max(values), "avg": sum(values) / len(values)}.items():
        for most in (0, 64, 300, None):
            b = aqp_aggregate(things, LmAtom(RED), agg, "id", Runtime(), column=None if agg == "count" else "x", max_calls=most, wave=16, max_error=-1)
            assert (b["lower"] is None or b["lower"] <= value + 1e-9) and (b["upper"] is None or b["upper"] >= value - 1e-9), (agg, most, b)
        assert b["lower"] == pytest.approx(value) == b["upper"]


def test_extreme_means_are_tight(spark):
    # all subsets of the unasked values by brute force
    rows = spark.createDataFrame([(i, "red a" if i < 2 else f"blue {i}", float(v)) for i, v in enumerate([10, 4, 1, 30, 7, 7, 25, 3])], "id long, name string, x double")
    b = aqp_aggregate(rows, LmAtom(RED), "avg", "id", Runtime(), column="x", max_calls=2, wave=2, max_error=-1)
    rest = [1, 30, 7, 7, 25, 3]
    means = [(14 + sum(v for j, v in enumerate(rest) if m >> j & 1)) / (2 + bin(m).count("1")) for m in range(64)]
    assert b["lower"] == pytest.approx(min(means)) and b["upper"] == pytest.approx(max(means))


def test_sampled_order_of_a_cascade(things):
    never = lm_map("Is an alarm to be heard?", "name", return_type="bool")
    e = And(LmAtom(lm_map("Is it a ring?", "name", return_type="bool")), LmAtom(never))
    written, ordered = Runtime(), Runtime(sampled=50)
    assert filtered(things, e, written).count() == filtered(things, e, ordered).count() == 0
    assert ordered.calls < written.calls


def test_groups_are_asked_level_by_level(spark):
    rows = spark.range(3000).selectExpr("IF(id % 10 = 0, 'b', IF(id % 10 = 1, NULL, 'a')) AS g", "concat(repeat('v', CAST(id % 91 AS INT)), id) AS text")
    rt = Runtime()
    got = {r.g: r.best for r in lm_agg(rows, "Which is the longest?", "text", ["g"], "best", rt, most=20).collect()}
    want = {}
    for r in rows.collect():
        want[r.g] = min(want.get(r.g, r.text), r.text, key=lambda t: (-len(t), t))
    assert got == want
    assert len(rt.ledger) >= 3 and rt.calls > 3000 / 20 and rt.total("in_tokens") > 0 and rt.ledger[-1]["calls"] == 3


def test_asks(spark):
    q = "What is the capital of the moon?"
    assert lm_ask(q, Runtime(provider=ReplayProvider({(q, '{"rows": []}'): "none"}))) == "none"
    assert lm_ask("Which is the longest?", Runtime()) == ""
    rt = Runtime()
    names = spark.range(500).selectExpr("concat(repeat('n', CAST(id % 83 AS INT)), id) AS name")
    assert lm_ask("Which is the longest?", rt, options=names, return_type="list[str]", quantifier="{2}", reduce="tree", chunk=3) == ["n" * 82 + "165", "n" * 82 + "248"]
    assert rt.total("in_tokens") > 0 and rt.calls == sum(r["calls"] for r in rt.ledger)


def test_decoding_ends_legally_at_its_limit():
    c = Constraint.list_of("string", 3, 3)
    text = constrained_decode(ScoredToyModel('["' + "x" * 500), c, limit=50)
    assert c.matches(text) and len(json.loads(text)) == 3


def test_frame_wrappers(things):
    f = LmFrame(things, Runtime()).where(LmAtom(RED)).with_lm("ring", RING)
    assert f.df.where("ring").count() == 43


def test_a_block_asks_about_returned_rows_only(things):
    words = lm_map("Which words describe it?", "name", return_type="list[str]")
    block = Select(And(LmAtom(RED), LmAtom(RING)), {"words": words}, limit=3)
    rt = Runtime()
    got = LmFrame(things, rt).execute(block, "id").df.collect()
    assert sorted((r.id, r.words[1]) for r in got) == [(0, "ring"), (14, "ring"), (28, "ring")]
    assert sum(r["inputs"] for r in rt.ledger if r["question"] == words.question) == 3
    ordered = Runtime()
    assert LmFrame(things, ordered).execute(Select(block.where, {"words": words}, limit=3, order_by=True)).df.count() == 43
    assert [x.split(". ")[1].split(":")[0] for x in LmFrame(things, rt).explain_lm(block).split("\n")][-2:] == ["limit", "map"]
