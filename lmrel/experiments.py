"""Further experiments: shapes of the SQL surface, joins of duplicates, extraction, streams, and measured comparisons."""

from __future__ import annotations

import tempfile
import time
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lmrel.functions import measures as M
from lmrel.functions.prompts import map_head
from lmrel.functions.skills import SKILLS
from lmrel.operators.executor import canon, key_of, with_answers
from lmrel.operators.frame import filtered
from lmrel.operators.pairs import lm_join
from lmrel.plans.ir import And, Native
from lmrel.plans.sql import run_sql
from lmrel.plans.strategies import MISSING, Workload, covered, run
from lmrel.session import ABLATION_LADDER, Runtime
from lmrel.sources.providers import PROFILES, NoisyProvider, RuleProvider
from lmrel.sources.tables import table
from lmrel.streaming.stream import lm_stream
from lmrel.workloads import _views, _wrong, atom, call, query, twin

_COLOUR = "CASE WHEN split_part({0}, ' ', 1) IN ('red', 'blue') THEN split_part({0}, ' ', 1) ELSE 'none' END"


# --- shapes of SQL ---------------------------------------------------------------------------------
@query(f"SELECT p.p_type, {_COLOUR.format('p.p_name')} AS colour, CAST(sum(l.l_quantity) AS DOUBLE) AS quantity FROM part p JOIN lineitem l ON l.l_partkey = p.p_partkey WHERE p.p_type IN ('PROMO', 'SMALL') GROUP BY 1, 2")
def lm_sql_join(spark: SparkSession, d: str) -> DataFrame:
    """Two aliased tables, a native filter, a call as a projection and a group key."""
    _views(spark, d, "part", "lineitem")
    mapped = "lm_map('What is the main colour?', p.p_name, options => array('red', 'blue', 'none'))"
    return run_sql(spark, f"SELECT p.p_type, {mapped} AS colour, CAST(sum(l.l_quantity) AS DOUBLE) AS quantity FROM v_part p JOIN v_lineitem l ON l.l_partkey = p.p_partkey WHERE p.p_type IN ('PROMO', 'SMALL') GROUP BY p.p_type, {mapped}", Runtime())


@query(f"WITH pairs AS (SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a, nation b WHERE a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey AND {twin('same_initial', 'a.n_name', 'b.n_name')}) SELECT a, b FROM pairs")
def lm_sql_pairs(spark, d):
    """A common table expression of self-joined pairs, judged outside of it."""
    _views(spark, d, "nation")
    return run_sql(spark, f"WITH pairs AS (SELECT a.n_nationkey AS a, b.n_nationkey AS b, a.n_name AS a_name, b.n_name AS b_name FROM v_nation a, v_nation b WHERE a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey) SELECT a, b FROM pairs WHERE lm_map('{SKILLS['same_initial'].question}', a_name, b_name)", Runtime())


@query("SELECT CAST(row_number() OVER (ORDER BY length(p_name) DESC, p_name) AS INTEGER) AS rank, p_name FROM (SELECT DISTINCT p_name FROM part) ORDER BY length(p_name) DESC, p_name LIMIT 3")
def lm_sql_topk(spark, d):
    _views(spark, d, "part")
    return run_sql(spark, "SELECT pos + 1 AS rank, col AS p_name FROM (SELECT posexplode(lm_ask('Which is the longest?', options => (SELECT DISTINCT p_name FROM v_part), return_type => 'list[str]', quantifier => '{3}')))", Runtime())


@query(f"SELECT CAST(10 AS BIGINT) AS n, TRUE AS all_right, count(DISTINCT p_name) > 0 AS fewer_than_all FROM part WHERE NOT ({twin('red', 'p_name')})")
def lm_sql_limit(spark, d):
    """LIMIT without an order: ten right rows, and fewer rows asked than a filter without it asks."""
    _views(spark, d, "part")
    rt = Runtime()
    rows = run_sql(spark, "SELECT p_name FROM v_part WHERE lm_map('Is it red?', p_name) = FALSE LIMIT 10", rt).collect()
    asked = sum(r["inputs"] for r in rt.ledger)
    return spark.createDataFrame([(len(rows), all(not r.p_name.startswith("red ") for r in rows), 0 < asked < table(spark, d, "part").count())], "n long, all_right boolean, fewer_than_all boolean")


@query(f"SELECT p_partkey FROM part WHERE {twin('red', 'p_name')} UNION ALL SELECT p_partkey FROM part WHERE p_type = 'PROMO' AND {twin('ring', 'p_name')}")
def lm_sql_union(spark, d):
    _views(spark, d, "part")
    return run_sql(spark, "SELECT p_partkey FROM v_part WHERE lm_map('Is it red?', p_name) UNION ALL SELECT p_partkey FROM v_part p WHERE p.p_type = 'PROMO' AND lm_map('Is it a ring?', p.p_name)", Runtime())


@query("SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE lower(c_mktsegment) = 'building') GROUP BY o_orderpriority HAVING count(*) > 5")
def lm_sql_subquery(spark, d):
    _views(spark, d, "orders", "customer")
    return run_sql(spark, "SELECT o_orderpriority, count(*) AS n FROM v_orders WHERE o_custkey IN (SELECT c.c_custkey FROM v_customer c WHERE lm_map('Which market is meant?', c.c_mktsegment, options => array('automobile', 'building', 'furniture', 'household', 'machinery')) = 'building') GROUP BY o_orderpriority HAVING count(*) > 5", Runtime())


@query(f"SELECT p_partkey, CASE WHEN {twin('red', 'p_name')} THEN 'r' WHEN p_size > 25 THEN 'large' ELSE 'p.other' END AS c FROM part WHERE ({twin('red', 'p_name')}) <> ({twin('ring', 'p_name')})")
def lm_sql_case(spark, d):
    """A call as a CASE condition, two calls in one comparison, a literal that looks like a column."""
    _views(spark, d, "part")
    return run_sql(spark, "SELECT p.p_partkey, CASE WHEN lm_map('Is it red?', p.p_name) THEN 'r' WHEN p_size > 25 THEN 'large' ELSE 'p.other' END AS c FROM v_part p WHERE lm_map('Is it red?', p.p_name) <> lm_map('Is it a ring?', p.p_name)", Runtime())


# --- joins of duplicates, extraction ---------------------------------------------------------------
@query(f"SELECT p_type, (SELECT count(*) FROM documents b WHERE {twin('same_initial', 'p_type', 'b.text')}) * count(*) AS n, (SELECT count(DISTINCT p_type) FROM part) * (SELECT count(DISTINCT text) FROM documents) AS calls FROM part GROUP BY p_type HAVING n > 0")
def lm_cross_few_many(spark, d):
    """Few distinct values crossed with many: calls follow distinct inputs, not pairs of rows."""
    rt = Runtime()
    types = table(spark, d, "part").groupBy("p_type").agg(F.count(F.lit(1)).alias("parts"))
    docs = table(spark, d, "documents").groupBy("text").agg(F.count(F.lit(1)).alias("docs"))
    yes = lm_join(types, docs, SKILLS["same_initial"].question, ("p_type",), ("text",), rt)
    return yes.groupBy("p_type").agg((F.first("parts") * F.sum("docs")).alias("n")).withColumn("calls", F.lit(rt.calls).cast("long"))


def _turns(spark, d):
    rows = table(spark, d, "conversations").select("conv_id", "turn", "text")
    return (rows.select("conv_id", F.col("turn").alias(t), F.col("text").alias(f"text_{t}")) for t in ("a", "b"))


_TURNS = f"FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND x.turn < y.turn WHERE {twin('same_language', 'x.text', 'y.text')}"


@query(f"SELECT x.conv_id, x.turn AS a, y.turn AS b {_TURNS}")
def lm_self_join_full(spark, d):
    a, b = _turns(spark, d)
    pairs = lm_join(a, b.withColumnRenamed("conv_id", "other"), SKILLS["same_language"].question, ("text_a",), ("text_b",), Runtime(), on="conv_id = other AND a < b")
    return pairs.select("conv_id", "a", "b")


@query(f"SELECT x.conv_id, x.turn AS a, y.turn AS b {_TURNS} ORDER BY x.conv_id, x.turn, y.turn LIMIT 10")
def lm_self_join_limit(spark, d):
    """The same with a limit over the pairs in key order: waves of pairs."""
    from lmrel.operators.frame import early_exit

    a, b = _turns(spark, d)
    pairs = a.join(b, "conv_id").where("a < b").withColumn("key", F.struct("conv_id", "a", "b"))
    return early_exit(pairs, atom("same_language", "text_a", "text_b"), 10, "key", Runtime()).select("conv_id", "a", "b")


@query("SELECT word, count(*) AS n FROM (SELECT unnest(string_split(regexp_extract(html, '<title>([^<]*)</title>', 1), ' ')) AS word FROM pages WHERE regexp_matches(html, '<title>[^<]+</title>')) GROUP BY word")
def lm_pages_words(spark, d):
    """Extraction: the words of every page's title as a list answer, exploded."""
    pages = table(spark, d, "pages").withColumn("title", F.regexp_extract("html", "<title>([^<]*)</title>", 1)).where("title <> ''")
    return with_answers(pages, call("tags", "title"), "words", Runtime()).select(F.explode("words").alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("n"))


# --- streams ---------------------------------------------------------------------------------------
@query(f"SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, {twin('failure', 'event_type')} AS failure, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling_lm(spark, d):
    """Tumbling days of a stream whose rows are answered by micro-batch; each batch's counts are written once under its epoch."""
    context = spark.sparkContext
    shared = context.getConf().get("spark.checkpoint.dir")
    folder = f"{shared}/stream-{context.applicationId}-{time.time_ns()}" if shared else tempfile.mkdtemp(prefix="stream")
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{d}/events.parquet")
    whole = path.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(path).isDirectory()
    reader = spark.readStream.schema(table(spark, d, "events").schema)
    stream = reader.parquet(f"{d}/events.parquet") if whole else reader.option("pathGlobFilter", "events.parquet").parquet(d)

    def sink(df: DataFrame, epoch: int) -> None:
        own = df.groupBy(F.window("ts", "1 day").alias("w"), "failure").agg(F.count(F.lit(1)).alias("n"))
        own.select(F.col("w.start").cast("date").cast("string").alias("day"), "failure", "n").write.mode("overwrite").parquet(f"{folder}/out/epoch={epoch}")

    lm_stream(stream, call("failure", "event_type"), "failure", Runtime(), sink, f"{folder}/checkpoint").awaitTermination()
    return spark.read.schema("day string, failure boolean, n long").parquet(f"{folder}/out").groupBy("day", "failure").agg(F.sum("n").alias("n"))


# --- measured comparisons --------------------------------------------------------------------------
def _pred(model: str, modality: str) -> str:
    p = PROFILES[model]
    return f"(({twin('red', 'p_name')}) <> ({_wrong('red', _INPUT, p.name, p.error[modality])}))"


_INPUT = "'{\"p_name\":\"' || p_name || '\"}'"
_F1 = "round(2.0 * count(*) FILTER (WHERE {0} AND {1}) / (count(*) FILTER (WHERE {0}) + count(*) FILTER (WHERE {1})), 6)"


@query(" UNION ALL ".join(
    f"SELECT '{m}' AS modality, own, hosted, round(own - hosted, 6) AS gap, CASE WHEN own - hosted > 0.02 THEN 'win' WHEN own - hosted >= -0.02 THEN 'tie' ELSE 'loss' END AS verdict FROM (SELECT {_F1.format(_pred('small-4b', m), '(' + twin('red', 'p_name') + ')')} AS own, {_F1.format(_pred('hosted', m), '(' + twin('red', 'p_name') + ')')} AS hosted FROM part)"
    for m in ("text", "image", "audio")
))
def quality_by_modality(spark, d):
    """F1 of a small local and of the hosted model for each modality, their gap and who wins (band 0.02)."""
    part, rows = table(spark, d, "part"), []
    truth = filtered(part, atom("red", "p_name"), Runtime()).select("p_partkey")
    from lmrel.plans.ir import LmAtom

    for m in ("text", "image", "audio"):
        own, hosted = (round(M.f1(filtered(part, LmAtom(call("red", "p_name", modality=m)), Runtime(provider=PROFILES[p])).select("p_partkey"), truth, ["p_partkey"])["f1"], 6) for p in ("small-4b", "hosted"))
        verdict = M.win_tie([own], [hosted])
        rows.append((m, own, hosted, round(own - hosted, 6), next(k for k in ("win", "tie", "loss") if verdict[k])))
    return spark.createDataFrame(rows, "modality string, own double, hosted double, gap double, verdict string")


@query(f"SELECT round(greatest(0, 1 - abs(answered - truth) / truth), 6) AS quality FROM (SELECT CAST(count(*) FILTER (WHERE ({twin('red', 'p_name')}) <> ({_wrong('red', _INPUT, 'noisy', 0.2)})) AS DOUBLE) AS answered, CAST(count(*) FILTER (WHERE {twin('red', 'p_name')}) AS DOUBLE) AS truth FROM part)")
def quality_agg_error(spark, d):
    """Quality of a count that a noisy model makes: one less the relative error."""
    part = table(spark, d, "part")
    answered, truth = (filtered(part, atom("red", "p_name"), rt).count() for rt in (Runtime(provider=NoisyProvider("noisy", error={"text": 0.2})), Runtime()))
    return spark.createDataFrame([(round(M.agg_quality(answered, truth), 6),)], "quality double")


_HEAD = len(map_head(SKILLS["red"].question, "boolean")) + len("Row: \nReply:")


@query(f"SELECT CAST(sum(i) AS BIGINT) AS in_tokens, CAST(sum(o) AS BIGINT) AS out_tokens, round(sum(i) * 0.30 / 1e6 + sum(o) * 2.5 / 1e6, 9) AS usd FROM (SELECT CAST(ceil(({_HEAD} + length({_INPUT})) / 4.0) AS BIGINT) AS i, CASE WHEN {twin('red', 'p_name')} THEN 1 ELSE 2 END AS o FROM (SELECT DISTINCT p_name FROM part))")
def cost_api_tokens(spark, d):
    """What a filter costs at token prices, from the prompts that were really sent."""
    rt = Runtime()
    filtered(table(spark, d, "part"), atom("red", "p_name"), rt).count()
    return spark.createDataFrame([(rt.total("in_tokens"), rt.total("out_tokens"), round(M.api_cost(rt.ledger), 9))], "in_tokens long, out_tokens long, usd double")


def _workloads(spark, d) -> dict[str, tuple[Workload, str]]:
    """Filter workloads with the SQL condition of each."""
    part, docs, events = (table(spark, d, t) for t in ("part", "documents", "events"))
    return {
        "clean_texts": (Workload(docs, And(Native("lang = 'en'"), atom("clean", "text")), "doc_id"), f"documents WHERE lang = 'en' AND {twin('clean', 'text')}"),
        "not_red": (Workload(part, And(Native("p_type = 'PROMO'"), atom("red", "p_name", template="{} = FALSE")), "p_partkey"), f"part WHERE p_type = 'PROMO' AND NOT ({twin('red', 'p_name')})"),
        "two_properties": (Workload(part, And(atom("thermal", "p_name"), atom("ring", "p_name")), "p_partkey"), f"part WHERE {twin('thermal', 'p_name')} AND {twin('ring', 'p_name')}"),
        "failures": (Workload(events, And(Native("value > 50"), atom("failure", "event_type")), "event_id"), f"events WHERE value > 50 AND {twin('failure', 'event_type')}"),
        "addresses": (Workload(docs, atom("email", "text"), "doc_id"), f"documents WHERE {twin('email', 'text')}"),
    }


_CONDITIONS = {
    "clean_texts": f"documents WHERE lang = 'en' AND {twin('clean', 'text')}", "not_red": f"part WHERE p_type = 'PROMO' AND NOT ({twin('red', 'p_name')})",
    "two_properties": f"part WHERE {twin('thermal', 'p_name')} AND {twin('ring', 'p_name')}", "failures": f"events WHERE value > 50 AND {twin('failure', 'event_type')}", "addresses": f"documents WHERE {twin('email', 'text')}",
}


@query(" UNION ALL ".join(f"SELECT '{w}' AS workload, '{s}' AS step, count(*) AS n FROM {c}" for w, c in _CONDITIONS.items() for s, _ in ABLATION_LADDER))
def ladder_same_rows(spark, d):
    """Every step of the ladder gives the same rows on every filter workload."""
    rows = []
    for name, (w, _) in _workloads(spark, d).items():
        for step, _ in ABLATION_LADDER:
            df, rt = run(w, step)
            rows.append((name, step, df.count()))
            rt.release()
    return spark.createDataFrame(rows, "workload string, step string, n long")


@query()
def ladder_calls(spark, d):
    """Calls of every filter workload with a limit of ten, step by step, with a model that also errs in form."""
    rows = []
    for name, (w, _) in _workloads(spark, d).items():
        for step, _ in ABLATION_LADDER:
            df, rt = run(Workload(w.df, w.where, w.key, 10), step, PROFILES["small-4b"])
            rows.append((name, step, df.count(), rt.calls, rt.total("malformed")))
            rt.release()
    return spark.createDataFrame(rows, "workload string, step string, n long, calls long, malformed long")


@query()
def five_runs(spark, d):
    """Mean and deviation of quality over five runs of a noisy model, its seconds, and cost by time."""
    rows = []
    for name, (w, _) in _workloads(spark, d).items():
        truth = run(w, "ours")[0].select(w.key)
        seen, began = [], time.perf_counter()
        for i in range(5):
            df, rt = run(w, "ours", NoisyProvider(f"run{i}", error={"text": 0.05}))
            seen.append(M.f1(df.select(w.key), truth, [w.key])["f1"])
            rt.release()
        seconds, mean = time.perf_counter() - began, sum(seen) / 5
        rows.append((name, round(mean, 6), round((sum((x - mean) ** 2 for x in seen) / 5) ** 0.5, 6), round(seconds / 5, 3), M.local_cost(seconds)))
    return spark.createDataFrame(rows, "workload string, f1_mean double, f1_std double, seconds double, usd double")


@query()
def concurrency_sweep(spark, d):
    """Seconds for the distinct part names under 8 to 128 requests at once, each of 20 simulated milliseconds."""
    part = table(spark, d, "part").withColumn("text", F.concat("p_name", F.lit(" "), F.col("p_partkey") % 512)).repartition(1).cache()
    part.count()
    rows = []
    for limit in (8, 16, 32, 64, 128):
        rt = Runtime(provider=RuleProvider("served", 0.02), max_concurrency=limit)
        got = M.benchmark(lambda rt=rt: filtered(part, atom("red", "text"), rt).count(), 1)
        rows.append((limit, rt.calls, round(got["mean"], 3)))
    part.unpersist()
    return spark.createDataFrame(rows, "concurrency long, calls long, seconds double")


#: What each of our filter, join and set workloads needs of an engine.
NEEDS = {
    "filter": set(), "projection": {"projection"}, "classes": {"projection"}, "json": {"projection"}, "top_k": {"rerank"}, "linking": set(), "cascade": set(),
    "pair_join": set(), "audio_filter": {"audio"}, "group_answer": {"lm_aggregation"}, "score_order": {"projection"}, "count": set(),
}


#: The inputs of these workloads, and the kinds that ask about them.
ASKED = {
    "texts": ("filter", "score_order", "count"), "grouped": ("group_answer",), "names": ("cascade",), "sold": ("projection",), "sizes": ("classes",),
    "props": ("json",), "turns": ("top_k",), "peaks": ("audio_filter",), "regions": ("linking",), "pairs": ("pair_join",),
}


def _inputs(spark, d) -> DataFrame:
    """(source, n): the distinct inputs of every source that has any, by the keys under which answers are kept."""
    docs, part, events = (table(spark, d, t) for t in ("documents", "part", "events"))
    sources = {
        "texts": (docs, ("text",)),
        "grouped": (docs.where("text IS NOT NULL"), ("lang", "text")),
        "names": (part, ("p_name",)),
        "sold": (part.where("p_type IN ('PROMO', 'SMALL')").join(table(spark, d, "lineitem"), F.col("l_partkey") == F.col("p_partkey"), "left_semi"), ("p_name",)),
        "sizes": (part, ("p_name", "p_size")),
        "props": (events, ("props",)),
        "turns": (table(spark, d, "conversations").where("role = 'user'"), ("text",)),
        "peaks": (events.groupBy("user_id").agg(F.max("value").alias("peak")), ("peak",)),
        "regions": (table(spark, d, "region"), ("r_name",)),
    }
    keys = [df.where(" OR ".join(f"{c} IS NOT NULL" for c in cs)).select(F.lit(s).alias("source"), key_of(canon(df, cs)).alias("k")) for s, (df, cs) in sources.items()]
    counts = reduce(DataFrame.unionByName, keys).distinct().groupBy("source").agg(F.count(F.lit(1)).alias("n"))
    names = part.agg(F.count_distinct("p_name").alias("n"), F.count_if(F.col("p_name").isNull()).alias("nulls"))
    pairs = names.select(F.lit("pairs").alias("source"), (F.col("n") * (F.col("n") + F.when(F.col("nulls") > 0, 2).otherwise(0))).alias("n"))
    return counts.unionByName(pairs.where("n > 0"))


_DISTINCT = {
    "texts": "SELECT DISTINCT text FROM documents WHERE text IS NOT NULL", "grouped": "SELECT DISTINCT lang, text FROM documents WHERE text IS NOT NULL",
    "names": "SELECT DISTINCT p_name FROM part WHERE p_name IS NOT NULL", "sold": "SELECT DISTINCT p_name FROM part WHERE p_name IS NOT NULL AND p_type IN ('PROMO', 'SMALL') AND p_partkey IN (SELECT l_partkey FROM lineitem)",
    "sizes": "SELECT DISTINCT p_name, p_size FROM part WHERE p_name IS NOT NULL OR p_size IS NOT NULL", "props": "SELECT DISTINCT props FROM events WHERE props IS NOT NULL",
    "turns": "SELECT DISTINCT text FROM conversations WHERE role = 'user' AND text IS NOT NULL", "peaks": "SELECT DISTINCT peak FROM (SELECT max(value) AS peak FROM events GROUP BY user_id) WHERE peak IS NOT NULL",
    "regions": "SELECT DISTINCT r_name FROM region WHERE r_name IS NOT NULL", "pairs": "SELECT a, b FROM (SELECT DISTINCT p_name AS a FROM part), (SELECT DISTINCT p_name AS b FROM part) WHERE a IS NOT NULL OR b IS NOT NULL",
}
_ABLE = [(s, k, not (m & n)) for s, m in sorted(MISSING.items()) for k, n in NEEDS.items()]


@query(f"""WITH asked AS ({" UNION ALL ".join(f"SELECT '{k}' AS kind, count(*) AS n FROM ({_DISTINCT[x]})" for x, kinds in ASKED.items() for k in kinds)}),
runs(strategy, kind, able) AS (VALUES {", ".join(f"('{s}', '{k}', {str(a).upper()})" for s, k, a in _ABLE)}),
t AS (SELECT strategy, count(n) FILTER (WHERE able) AS supported, count(n) AS kinds, CAST(coalesce(sum(n) FILTER (WHERE able), 0) AS BIGINT) AS inputs, sum(n) AS total FROM runs LEFT JOIN (SELECT * FROM asked WHERE n > 0) USING (kind) GROUP BY strategy)
SELECT strategy, supported, round(100.0 * supported / CAST(nullif(kinds, 0) AS DOUBLE), 4) AS percent, inputs, round(100.0 * inputs / CAST(total AS DOUBLE), 4) AS inputs_percent FROM t""")
def coverage_by_strategy(spark, d):
    """The share of the kinds of workload that have inputs in the tables, and of these inputs, that each strategy can run, from what they need and what it lacks."""
    able = spark.createDataFrame([(s, k, x, covered(s, NEEDS[k])) for s in sorted(MISSING) for x, kinds in ASKED.items() for k in kinds], "strategy string, kind string, source string, able boolean")
    runs, share = F.when(F.col("able"), F.col("n")), lambda a, b: F.round(F.try_divide(F.lit(100.0) * a, b.cast("double")), 4)
    return able.join(F.broadcast(_inputs(spark, d)), "source", "left").groupBy("strategy").agg(
        F.count(runs).alias("supported"), share(F.count(runs), F.count("n")).alias("percent"),
        F.coalesce(F.sum(runs), F.lit(0)).cast("long").alias("inputs"), share(F.sum(runs), F.sum("n")).alias("inputs_percent"),
    )
