"""Coverage counts the kinds of workload, and their inputs, that the tables hold."""

import duckdb

from lmrel import experiments
from lmrel.plans.strategies import MISSING, covered
from lmrel.workloads import ORACLES

SCHEMAS = {
    "documents": "doc_id long, text string, lang string", "part": "p_partkey long, p_name string, p_type string, p_size int", "lineitem": "l_partkey long",
    "events": "user_id long, value double, props string", "conversations": "role string, text string", "region": "r_name string",
}
TEXTS = [(i, None if i % 9 == 0 else f"text {i % 31}", None if i % 4 == 0 else "en") for i in range(200)]
PARTS = [(i, None if i % 13 == 0 else f"red {i % 17}", "PROMO" if i % 2 else "LARGE", None if i % 5 == 0 else i % 3) for i in range(150)]
EVENTS = [(i % 20, [-0.0, 0.0, None, float("nan"), 2.5][i % 5], f'{{"k": {i % 7}}}') for i in range(100)]
ROWS = {"documents": TEXTS, "part": PARTS, "lineitem": [(3,), (3,), (None,), (5,), (20,), (999,)], "events": EVENTS, "conversations": [("user", "a"), ("user", "a"), ("user", None), ("system", "b")], "region": []}


def _got(spark, folder, rows):
    for t, schema in SCHEMAS.items():
        spark.createDataFrame(rows[t], schema).coalesce(1).write.parquet(f"{folder}/{t}.parquet")
    con = duckdb.connect()
    for t in SCHEMAS:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{folder}/{t}.parquet/*.parquet')")
    out = experiments.coverage_by_strategy(spark, str(folder))
    got = sorted(map(tuple, out.collect()))
    cursor = con.execute(ORACLES["coverage_by_strategy"])
    assert [c[0] for c in cursor.description] == out.columns and sorted(cursor.fetchall()) == got
    return {r[0]: r[1:] for r in got}


def test_coverage_counts_what_the_tables_hold(spark, tmp_path):
    names = {n for _, n, _, _ in PARTS}
    texts = len({t for _, t, _ in TEXTS if t})
    inputs = {
        "filter": texts, "score_order": texts, "count": texts, "group_answer": len({(g, t) for _, t, g in TEXTS if t}), "cascade": len(names - {None}), "classes": len({(n, s) for _, n, _, s in PARTS if n or s is not None}),
        "projection": 2, "json": 7, "top_k": 1, "audio_filter": 3, "pair_join": len(names) ** 2 - 1,
    }  # fmt: skip  # both zeros are one peak, all NaN are one, and 2.5
    got = _got(spark, tmp_path, ROWS)
    assert None in names and set(inputs) == set(experiments.NEEDS) - {"linking"}  # no region, so there is nothing to link
    for s in MISSING:
        own = [n for k, n in inputs.items() if covered(s, experiments.NEEDS[k])]
        assert got[s] == (len(own), round(100 * len(own) / 11, 4), sum(own), round(100 * sum(own) / sum(inputs.values()), 4))


def test_coverage_of_nothing(spark, tmp_path):
    assert _got(spark, tmp_path, dict.fromkeys(SCHEMAS, [])) == dict.fromkeys(MISSING, (0, None, 0, None))
