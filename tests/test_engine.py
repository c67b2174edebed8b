"""Planner, automata, answers, early exit, joins, bounds and measures."""

import itertools
import json
import random

import pytest

from lmrel.functions import measures as M
from lmrel.functions.constraints import Constraint, ScoredToyModel, constrained_decode, parse_lenient
from lmrel.functions.prompts import render_ask_prompt, render_map_prompt
from lmrel.functions.types import infer_return_type, parse_quantifier, parse_type
from lmrel.operators.approximate import aqp_aggregate
from lmrel.operators.ask import ContextTooLarge, lm_ask
from lmrel.operators.executor import with_answers
from lmrel.operators.frame import early_exit, filtered
from lmrel.operators.pairs import TooManyPairs, lm_join
from lmrel.plans.ir import And, LmAtom, Native, Not, Or, Select, calls, is_cascadable, is_early_exitable, relax, rendered
from lmrel.plans.sql import clauses, find_calls
from lmrel.plans.strategies import STRATEGIES, Workload, run
from lmrel.session import BudgetExceeded, Features, Runtime, lm_map
from lmrel.sources.providers import NoisyProvider
from lmrel.sources.tables import AnswerCache
from lmrel.streaming.stream import lm_stream

RED, RING = lm_map("Is it red?", "name", return_type="bool"), lm_map("Is it a ring?", "name", return_type="bool")


@pytest.fixture(scope="module")
def things(spark):
    rows = [(i, f"{c} {o}" if i % 11 else None, i % 4) for i, (c, o) in enumerate(itertools.product(["red", "blue", "hot"], ["ring", "cog", "pin"] * 8))]
    return spark.createDataFrame(rows, "id long, name string, kind int").cache()


def test_types():
    assert parse_type("list[str]") == "array<string>" and parse_type("decimal(9,2)") == "decimal(9,2)"
    assert [parse_quantifier(q) for q in ("*", "+", "?", "{3}", "{1,2}", "{2,}")] == [(0, None), (1, None), (0, 1), (3, 3), (1, 2), (2, None)]
    assert [infer_return_type(t) for t in ("{}", "{} = FALSE", "{} > 3", "{} / 2", "{} = 'a'", "explode({})")] == ["bool", "bool", "int", "float", "str", "list[str]"]


@pytest.mark.parametrize("c, good, bad", [
    (Constraint.from_type("boolean"), ["true", "false"], ["True", "yes", ""]), (Constraint.from_type("bigint"), ["-12", "0"], ["1.5", "-", "x"]),
    (Constraint.from_type("date"), ["2024-02-30"], ["2024-13-01", "24-01-01"]), (Constraint.from_options(["a", "ab"]), ["a", "ab"], ["b", "abc"]),
    (Constraint.list_of("string", 1, 2), ['["x"]', '["x", "y"]'], ["[]", '["x", "y", "z"]']), (Constraint.list_of("bigint", 2, 2), ["[1, 2]"], ["[1]"]),
    (Constraint.from_struct("struct<k:bigint,band:string>"), ['{"k": 1, "band": "low"}'], ['{"band": "low"}']),
])
def test_constraints(c, good, bad):
    assert all(c.matches(x) for x in good) and not any(c.matches(x) for x in bad)
    for raw in [*good, *bad, "Well, it is: " + good[0] + "!!", "zzz", "{"]:
        text = constrained_decode(ScoredToyModel(raw), c)
        assert c.matches(text), (raw, text)
        json.loads(c.json(text))
    assert constrained_decode(ScoredToyModel("Well, I would say it is: " + good[0] + "!!"), c) == good[0]
    assert parse_lenient("It is " + good[0], c) is None


def test_relaxation_keeps_every_answer(spark):
    values = {"a": [True, False, None], "b": [True, False, None]}
    r = random.Random(1)

    def tree(depth):
        if depth == 0 or r.random() < 0.25:
            return r.choice([Native("a"), Native("b IS NULL"), Native("b = FALSE"), LmAtom(RED, "{}"), LmAtom(RING, "{} = FALSE"), LmAtom(RED, "{} IS NULL")])
        return r.choice([lambda: Not(tree(depth - 1)), lambda: And(tree(depth - 1), tree(depth - 1)), lambda: Or(tree(depth - 1), tree(depth - 1))])()

    rows = list(itertools.product(values["a"], values["b"], values["a"], values["b"]))
    df = spark.createDataFrame(rows, "a boolean, b boolean, x boolean, y boolean").coalesce(1)
    exprs = [tree(4) for _ in range(40)]
    names = {RED: "x", RING: "y"}
    wrong = df.selectExpr(*(f"count(CASE WHEN {rendered(e, names)} AND NOT coalesce({relax(e) or 'TRUE'}, FALSE) THEN 1 END) AS c{i}" for i, e in enumerate(exprs))).first()
    assert set(wrong) == {0}
    assert all("{}" not in (relax(e) or "") for e in exprs)


def test_guards():
    both = And(LmAtom(RED), LmAtom(RING))
    assert is_cascadable(both) and not is_cascadable(Or(LmAtom(RED), LmAtom(RING))) and not is_cascadable(LmAtom(RED))
    assert is_early_exitable(Select(both, limit=3)) and not is_early_exitable(Select(both, limit=3, order_by=True)) and not is_early_exitable(Select(both))
    assert calls(And(LmAtom(RED), Not(LmAtom(RED)))) == [RED]


def test_features_agree(things):
    e = And(Or(Native("kind = 1"), LmAtom(RED)), LmAtom(RING, "{} = FALSE"), Not(LmAtom(lm_map("Is it hot or cold?", "name"))))
    want = {r.id for r in things.collect() if r.name and (r.kind == 1 or r.name.startswith("red")) and not r.name.endswith("ring") and not r.name.startswith("hot")}
    for ee, cf, cd, ed in itertools.product([False, True], repeat=4):
        if ee == cd and cf == ed:
            assert {r.id for r in filtered(things, e, Runtime(features=Features(ee, cf, cd, ed))).collect()} == want


def test_calls_and_cache(spark, things, tmp_path):
    rt = Runtime(cache=AnswerCache(spark, str(tmp_path)))
    got = with_answers(things, RED, "red", rt)
    assert rt.calls == things.where("name IS NOT NULL").select("name").distinct().count()
    assert got.where("name IS NULL AND red IS NOT NULL").count() == 0 and got.count() == things.count()
    again = Runtime(cache=AnswerCache(spark, str(tmp_path)))
    assert with_answers(things, RED, "red", again).where("red").count() == got.where("red").count() and again.calls == 0
    with pytest.raises(BudgetExceeded):
        with_answers(things, RING, "ring", Runtime(max_calls=2))
    dry = Runtime(dry=True)
    with_answers(things, RING, "ring", dry)
    assert dry.calls == rt.calls


def test_early_exit(things):
    e = And(LmAtom(RED), LmAtom(RING))
    want = [r.id for r in filtered(things, e, Runtime()).orderBy("id").limit(3).collect()]
    for f in (Features(), Features(ed=False), Features(ee=False)):
        assert [r.id for r in early_exit(things, e, 3, "id", Runtime(features=f), concurrency=2).collect()] == want
    eager, ours = (run(Workload(things, e, "id", 3), s)[1].calls for s in ("eager", "ours"))
    assert ours <= eager and set(STRATEGIES) >= {"eager", "lazy", "aqp", "v0", "ours"}


def test_noise_and_constraints(things):
    noisy = NoisyProvider("n", malformed=0.5, error={"text": 0.0})
    on, off = Runtime(provider=noisy), Runtime(provider=noisy, features=Features(cd=False))
    truth = filtered(things, LmAtom(RED), Runtime()).count()
    assert filtered(things, LmAtom(RED), on).count() == truth >= filtered(things, LmAtom(RED), off).count()
    assert off.total("malformed") > 0 and M.format_validity(on.ledger) == 1.0


def test_joins(things):
    left = things.selectExpr("id AS a", "name AS an").where("an IS NOT NULL").limit(20).cache()
    right = things.selectExpr("id AS b", "name AS bn").where("bn IS NOT NULL").limit(20).cache()
    q = "Are both the same kind of thing?"
    want = {(x.a, y.b) for x in left.collect() for y in right.collect() if x.an.split()[1] == y.bn.split()[1]}
    for rt in (Runtime(), Runtime(features=Features(ed=False))):
        assert {(r.a, r.b) for r in lm_join(left, right, q, ("an",), ("bn",), rt).collect()} == want
    assert lm_join(left, right, q, ("an",), ("bn",), Runtime(), how="left_anti").count() == 0
    with pytest.raises(TooManyPairs):
        lm_join(left, right, q, ("an",), ("bn",), Runtime(max_pairs=3))


def test_ask(spark, things):
    names = things.select("name")
    assert lm_ask("Which is the longest?", Runtime(), options=names) == "blue ring"
    assert lm_ask("Which is the longest?", Runtime(), options=names, return_type="list[str]", quantifier="{2}", reduce="tree", chunk=3) == ["blue ring", "blue cog"]
    assert lm_ask("Which is the longest?", Runtime(), options=names.limit(0)) is None
    with pytest.raises(ContextTooLarge):
        lm_ask("Which is the longest?", Runtime(), options=spark.range(6000).selectExpr("cast(id AS string) AS s"))


def test_bounds_hold(things):
    rows = things.where("name IS NOT NULL")
    atom = LmAtom(RED)
    values = [r.kind for r in rows.collect() if r.name.startswith("red")]
    exact = {"count": len(values), "sum": sum(values), "min": min(values), "max": max(values), "avg": sum(values) / len(values)}
    for agg, value in exact.items():
        for budget in (20, None):
            b = aqp_aggregate(rows, atom, agg, "id", Runtime(), column=None if agg == "count" else "kind", max_calls=budget, wave=20 if budget else 100, max_error=-1)
            assert (b["lower"] is None or b["lower"] <= value + 1e-9) and (b["upper"] is None or b["upper"] >= value - 1e-9)
        assert b["lower"] == pytest.approx(value) and b["upper"] == pytest.approx(value)


def test_sql_text():
    q = "SELECT a, lm_map('x, (y)', t.a) FROM t WHERE lm_map('q''s', b) = FALSE AND c IN (1, 2) ORDER BY a LIMIT 3"
    assert [x[2] for x in find_calls(q, "lm_map")] == [["'x, (y)'", "t.a"], ["'q''s'", "b"]]
    assert clauses(q)["LIMIT"] == "3" and clauses(q)["FROM"] == "t"


def test_measures(spark):
    df = spark.createDataFrame([(1, 10.0), (2, 20.0), (2, 30.0), (4, 5.0)], "a int, b double")
    assert M.spearman(df, "a", "b") == pytest.approx(-0.3162, abs=1e-3)
    one = spark.createDataFrame([(1,), (2,)], "k int")
    assert M.f1(one, one, ["k"])["f1"] == 1.0 and M.f1(one.limit(0), one, ["k"])["f1"] == 0.0 and M.f1(one.limit(0), one.limit(0), ["k"])["f1"] == 1.0
    assert M.local_cost(55.15 * 5) == pytest.approx(0.0138, abs=1e-4) and M.local_cost(1522.77 * 5) == pytest.approx(0.381, abs=1e-3)
    assert M.carbon(81)["kwh"] == pytest.approx(27.2, abs=0.1) and M.carbon(81)["kg"] == pytest.approx(11.4, abs=0.1)
    assert M.win_tie([0.5, 0.5, 0.5], [0.48, 0.6, 0.1]) == {"win": 1, "tie": 1, "loss": 1, "share": 2 / 3}
    assert M.average_system({"x": {"q": 1.0, "p": None}, "y": {"q": 3.0, "p": 4.0}}) == 3.0
    assert M.count_wins({"x": {"q": 1.0}, "y": {"q": 2.0}}) == {"x": 0, "y": 1} and round(M.coverage({"x": 54})["x"], 2) == 98.18
    assert M.agg_quality(9, 10) == pytest.approx(0.9) and M.agg_quality(0, 0) == 1.0 and M.ee_waste(12, 10) == 2


def test_prompts():
    a, b = (render_map_prompt("q", x, "boolean", ("u", "v")) for x in ('{"n":1}', '{"n":2}'))
    assert a[: a.index("Row:")] == b[: b.index("Row:")] and "exactly 3" in render_ask_prompt("q", None, "array<string>", ["a"], (3, 3))


def test_stream(spark, things, tmp_path):
    things.where("name IS NOT NULL").repartition(3).write.parquet(f"{tmp_path}/in")
    rt, seen = Runtime(), []
    stream = spark.readStream.schema("id long, name string, kind int").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    lm_stream(stream, RED, "red", rt, lambda df, epoch: seen.extend(df.where("red").select("id").collect()), f"{tmp_path}/cp").awaitTermination(120)
    assert sorted(r.id for r in seen) == sorted(r.id for r in filtered(things, LmAtom(RED), Runtime()).collect())
    assert rt.calls == things.where("name IS NOT NULL").select("name").distinct().count()
