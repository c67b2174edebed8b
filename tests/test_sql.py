"""The SQL surface against plain Python over small views."""

import itertools

import pytest

from lmrel.plans.sql import run_sql, tokens
from lmrel.session import Features, Runtime
from lmrel.sources.providers import NoisyProvider

KIND, RED, RING = "'Are both the same kind of thing?'", "'Is it red?'", "'Is it a ring?'"


@pytest.fixture(scope="module")
def rows(spark):
    out = [(i, f"{c} {o}", i % 4, f"p.{i % 3}") for i, (c, o) in enumerate(itertools.product(["red", "blue", "hot"], ["ring", "cog", "pin"] * 4))]
    spark.createDataFrame(out, "id long, name string, kind int, code string").createOrReplaceTempView("things")
    spark.createDataFrame([(i, f"{o} lover", o) for i, o in enumerate(["ring", "cog", "pin"])], "uid long, name string, likes string").createOrReplaceTempView("people")
    return out


def red(r):
    return r[1].startswith("red")


def ring(r):
    return r[1].endswith("ring")


def same(a, b):
    return a.split()[1] == b.split()[1]


def got(spark, sql, **more):
    return [tuple(r) for r in run_sql(spark, sql, Runtime(**more)).collect()]


def test_tokens_leave_literals_alone():
    q = "SELECT 'lm_map(x' AS a, `lm_map` -- lm_map('q', x)\n FROM t WHERE b = 'it''s' /* lm_ask( */"
    assert [t.text for t in tokens(q)] == ["SELECT", "'lm_map(x'", "AS", "a", ",", "`lm_map`", "FROM", "t", "WHERE", "b", "=", "'it''s'"]


def test_aliased_join(spark, rows):
    q = f"SELECT t.id, p.name FROM things t JOIN people AS p ON p.likes = split(t.name, ' ')[1] WHERE t.kind > 1 AND lm_map({RED}, t.name) AND t.code <> 'p.1'"
    assert sorted(got(spark, q)) == sorted((r[0], r[1].split()[1] + " lover") for r in rows if r[2] > 1 and red(r) and r[3] != "p.1")


def test_self_join_pairs_in_a_cte(spark, rows):
    q = f"WITH pairs AS (SELECT a.id AS a, b.id AS b, a.name AS an, b.name AS bn FROM things a, things b WHERE a.id < b.id AND a.kind = b.kind), few AS (SELECT * FROM pairs WHERE a < 9) SELECT few.a, b FROM few WHERE lm_map({KIND}, an, few.bn)"
    assert sorted(got(spark, q)) == sorted((x[0], y[0]) for x in rows for y in rows if x[0] < y[0] and x[2] == y[2] and x[0] < 9 and same(x[1], y[1]))


def test_join_on_a_call(spark, rows):
    want = sorted((x[0], y[0]) for x in rows for y in rows if same(x[1], y[1]))
    rt = Runtime()
    assert sorted(tuple(r) for r in run_sql(spark, f"SELECT a.id, b.id AS other FROM things a JOIN things b ON lm_map({KIND}, a.name, b.name)", rt).collect()) == want
    assert rt.calls == 81  # nine distinct names on either side
    q = f"SELECT a.id, b.id AS other FROM things a INNER JOIN things b ON a.kind = b.kind AND lm_map({KIND}, a.name, b.name) AND a.id < b.id"
    assert sorted(got(spark, q)) == sorted((x[0], y[0]) for x in rows for y in rows if x[2] == y[2] and x[0] < y[0] and same(x[1], y[1]))
    with pytest.raises(ValueError):
        got(spark, f"SELECT * FROM things a LEFT JOIN things b ON lm_map({KIND}, a.name, b.name)")


def test_star_and_qualified_star(spark, rows):
    out = run_sql(spark, f"SELECT * FROM things t JOIN people p ON p.uid = t.kind WHERE lm_map({RED}, t.name)", Runtime())
    assert out.columns == ["id", "name", "kind", "code", "uid", "name", "likes"] and out.count() == sum(red(r) and r[2] < 3 for r in rows)
    assert run_sql(spark, f"SELECT t.* FROM things t JOIN people p ON p.uid = t.kind WHERE lm_map({RED}, t.name)", Runtime()).columns == ["id", "name", "kind", "code"]


def test_subqueries_and_set_operations(spark, rows):
    ids = lambda f: {r[0] for r in rows if f(r)}
    q = f"SELECT id FROM things WHERE lm_map({RED}, name) UNION SELECT id FROM things WHERE lm_map({RING}, name) EXCEPT SELECT id FROM things WHERE kind = 1 ORDER BY id LIMIT 100"
    assert [x for (x,) in got(spark, q)] == sorted((ids(red) | ids(ring)) - ids(lambda r: r[2] == 1))
    q = f"SELECT uid FROM people WHERE uid IN (SELECT kind FROM things WHERE lm_map({RED}, name) AND id < 2)"
    assert sorted(got(spark, q)) == [(0,), (1,)]
    q = f"SELECT n FROM (SELECT kind, count(*) AS n FROM things t WHERE NOT lm_map({RING}, t.name) GROUP BY kind) s WHERE s.kind IN (SELECT uid FROM people) AND s.kind = 2"
    assert got(spark, q) == [(sum(r[2] == 2 and not ring(r) for r in rows),)]


def test_case_having_aggregates_and_order(spark, rows):
    q = f"SELECT id, CASE WHEN lm_map({RED}, name) THEN 'r' WHEN kind = 1 THEN 'k' ELSE 'o' END AS c FROM things ORDER BY id"
    assert got(spark, q) == [(r[0], "r" if red(r) else "k" if r[2] == 1 else "o") for r in rows]
    q = "SELECT lm_map('What is the main colour?', name, options => array('red', 'blue', 'none')) AS colour, count(*) AS n FROM things GROUP BY colour HAVING count(*) > 1 ORDER BY colour"
    assert got(spark, q) == [("blue", 12), ("none", 12), ("red", 12)]
    q = "SELECT kind, AVG(lm_map('How long-winded is it, from 1 to 5?', name)) AS score, sum(lm_map('How long-winded is it, from 1 to 5?', name)) + 1 AS s FROM things GROUP BY kind ORDER BY 1"
    assert got(spark, q) == [(k, 1.0, 10.0) for k in range(4)]
    q = "SELECT id FROM things WHERE lm_map('How long-winded is it, from 1 to 5?', name) + kind > 3 ORDER BY id"
    assert [x for (x,) in got(spark, q)] == [r[0] for r in rows if 1 + r[2] > 3]


def test_two_calls_in_one_comparison(spark, rows):
    q = "SELECT a.id, b.uid FROM things a JOIN people b ON a.id = b.uid WHERE lm_map('Which words describe it?', a.name, return_type => 'list[str]') = lm_map('Which words describe it?', b.name, return_type => 'list[str]') OR a.id = 1"
    assert got(spark, q) == [(1, 1)]
    q = f"SELECT id FROM things WHERE lm_map({RED}, name) = lm_map({RING}, name) ORDER BY id"
    assert [x for (x,) in got(spark, q)] == [r[0] for r in rows if red(r) == ring(r)]


def test_literals_are_kept(spark, rows):
    q = f"SELECT id, 'p.{{}}' AS x, 'lm_answer_0' AS y FROM things p WHERE p.code = 'p.1' AND (lm_map({RED}, p.name) = TRUE OR concat('{{}}', code) = CASE WHEN lm_map({RED}, name) THEN 'a{{}}b' ELSE '{{1}}' END)"
    assert sorted(got(spark, q)) == sorted((r[0], "p.{}", "lm_answer_0") for r in rows if r[3] == "p.1" and red(r))


def test_between_and_not(spark, rows):
    q = f"SELECT id FROM things WHERE id BETWEEN 2 AND 20 AND NOT (lm_map({RED}, name) OR kind NOT BETWEEN 1 AND 2) ORDER BY id"
    assert [x for (x,) in got(spark, q)] == [r[0] for r in rows if 2 <= r[0] <= 20 and not (red(r) or not 1 <= r[2] <= 2)]


def test_limit_stops_asking(spark):
    spark.range(20_000).selectExpr("id", "concat(IF(id % 3 = 0, 'red', 'blue'), ' thing', CAST(id AS STRING)) AS name").createOrReplaceTempView("many")
    rt = Runtime()
    out = run_sql(spark, f"SELECT id, lm_map('Which words describe it?', name, return_type => 'list[str]') AS w FROM many WHERE lm_map({RED}, name) LIMIT 3", rt).collect()
    assert len(out) == 3 and all(r.id % 3 == 0 and r.w[0] == "red" for r in out)
    assert rt.calls <= 60  # a wave of the filter, and the projection of three rows only
    rt = Runtime()
    assert run_sql(spark, f"SELECT count(*) AS n FROM many WHERE lm_map({RED}, name) LIMIT 3", rt).first().n == 6667 and rt.calls == 20_000


def test_asks_and_top_k(spark, rows):
    q = "SELECT pos + 1 AS rank, col AS name FROM (SELECT posexplode(lm_ask('Which is the longest?', options => (SELECT name FROM things), return_type => 'list[str]', quantifier => '{2}')))"
    assert got(spark, q) == [(1, "blue ring"), (2, "blue cog")]
    q = f"WITH r AS (SELECT name FROM things WHERE lm_map({RED}, name)) SELECT id FROM things WHERE name = lm_ask('Which is the longest?', options => (SELECT name FROM r)) ORDER BY id LIMIT 2"
    assert got(spark, q) == [(0,), (3,)]


def test_types_from_what_stands_around(spark, rows):
    noisy = NoisyProvider("n", malformed=0.5, error={"text": 0.0})
    for features in (Features(), Features(cf=False), Features(ed=False)):
        q = f"SELECT id FROM things WHERE lm_map({RED}, name) = (kind < 9) AND lm_map('What is the main colour?', name, options => array('red', 'blue', 'none')) = split(name, ' ')[0]"
        assert len(got(spark, q, features=features, provider=noisy)) == 12
