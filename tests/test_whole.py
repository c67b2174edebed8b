"""Queries take part with all rows: many options, many names, long texts."""

from collections import Counter

import pytest

from lmrel import workloads
from lmrel.functions.skills import SKILLS
from lmrel.operators import ask
from lmrel.operators.ask import lm_link, lm_topk
from lmrel.session import Runtime


def test_many_options_by_a_tree(spark, monkeypatch):
    q, names = SKILLS["longest"].question, spark.range(6000).selectExpr("concat(repeat('x', CAST(id % 97 AS INT)), CAST(id AS STRING)) AS name")
    wanted = sorted((r.name for r in names.collect()), key=lambda t: (-len(t), t))
    assert [r.name for r in lm_topk(names, q, "name", 3, Runtime()).orderBy("rank").collect()] == wanted[:3]
    assert [r.name for r in lm_link(names, q, "name", Runtime(), names).collect()] == wanted[:1]
    few = names.where("length(name) > 96")
    one = lm_topk(few, q, "name", 3, Runtime()).collect()
    monkeypatch.setattr(ask, "collect_context", lambda df, inner=ask.collect_context: inner(df, max_chars=4000))
    monkeypatch.setattr(ask, "MAX_CHARS", 4000)
    assert lm_topk(few, q, "name", 3, Runtime()).collect() == one
    with pytest.raises(ask.ContextTooLarge):
        lm_topk(spark.createDataFrame([("x" * 3000,), ("y" * 3000,)], "name string"), q, "name", 2, Runtime())


def test_groups_of_long_texts(spark, tmp_path):
    rows = [(i, f"{'word ' * (i % 40)}{i}", "en" if i % 3 else "de") for i in range(700)] + [(900, "long " * 20000, "en"), (901, None, "fr")]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.lang: r.text for r in workloads.QUERIES["lm_group_ask"](spark, str(tmp_path)).collect()}
    assert got == {g: min((t for _, t, x in rows if x == g and t), key=lambda t: (-len(t), t)) for g in ("en", "de")}


def test_all_parts_take_part(spark, tmp_path):
    names = [(i * 7 % 1301, f"c{i % 11} {'ring' if i % 3 else 'cog'}") for i in range(1301)]
    spark.createDataFrame(names, "p_partkey long, p_name string").write.parquet(f"{tmp_path}/part.parquet")
    kind = lambda t: t.split()[1]
    pairs = Counter((x, y) for a, x in names for b, y in names if a < b and kind(x) == kind(y))
    assert {(r.a_name, r.b_name): r.n for r in workloads.QUERIES["lm_join_same_kind"](spark, str(tmp_path)).collect()} == pairs
    cross = {x: sum(y == x for _, y in names) * sum(kind(y) == kind(x) for _, y in names) for _, x in names}
    assert {r.p_name: r.n for r in workloads.QUERIES["lm_cross_dedup"](spark, str(tmp_path)).collect()} == cross


def test_all_names_are_paid_for(spark, tmp_path):
    names = [f"part {i}" for i in range(1500)]
    spark.createDataFrame([(i, t) for i, t in enumerate(names)], "p_partkey long, p_name string").write.parquet(f"{tmp_path}/part.parquet")
    assert tuple(workloads.QUERIES["cost_api"](spark, str(tmp_path)).first()) == (sum(-(-len(t) // 4) for t in names), 1500)
