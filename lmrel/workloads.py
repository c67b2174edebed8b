"""Experiment workloads on the given tables: one query each, with the SQL that has no model in it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from lmrel.functions import measures as M
from lmrel.functions.skills import SKILLS
from lmrel.operators.approximate import aqp_aggregate, proxy_cascade
from lmrel.operators.ask import lm_agg, lm_ask, lm_link, lm_topk, retrieve
from lmrel.operators.executor import with_answers
from lmrel.operators.frame import LmFrame, early_exit, filtered
from lmrel.operators.pairs import lm_join
from lmrel.plans.ir import And, LmAtom, Native, Not, Or
from lmrel.plans.sql import run_sql
from lmrel.plans.strategies import STRATEGIES, Workload, ablate, run
from lmrel.session import LmCall, Runtime
from lmrel.sources.providers import PROFILES, NoisyProvider
from lmrel.sources.tables import table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def call(skill: str, *columns: str, **more) -> LmCall:
    s = SKILLS[skill]
    return LmCall(s.question, columns, s.dtype, more.pop("options", s.options), **more)


def atom(skill: str, *columns: str, template: str = "{}") -> LmAtom:
    return LmAtom(call(skill, *columns), template)


def twin(skill: str, *columns: str) -> str:
    return SKILLS[skill].twin(*columns)


# --- row-wise filters ---------------------------------------------------------------------------
@query(f"SELECT doc_id, lang FROM documents WHERE {twin('clean', 'text')}")
def lm_filter_true(spark: SparkSession, d: str) -> DataFrame:
    return filtered(table(spark, d, "documents"), atom("clean", "text"), Runtime()).select("doc_id", "lang")


@query(f"SELECT p_partkey, p_name FROM part WHERE p_type = 'PROMO' AND NOT ({twin('red', 'p_name')}) ORDER BY p_partkey LIMIT 10")
def lm_filter_false_native(spark, d):
    e = And(Native("p_type = 'PROMO'"), atom("red", "p_name", template="{} = FALSE"))
    return early_exit(table(spark, d, "part"), e, 10, "p_partkey", Runtime()).select("p_partkey", "p_name")


@query(f"SELECT p_partkey FROM part WHERE p_type = 'PROMO' OR ({twin('red', 'p_name')})")
def lm_filter_or_native(spark, d):
    return filtered(table(spark, d, "part"), Or(Native("p_type = 'PROMO'"), atom("red", "p_name")), Runtime()).select("p_partkey")


@query(f"SELECT p_partkey FROM part WHERE NOT (p_type = 'PROMO' OR {twin('red', 'p_name')})")
def lm_filter_not(spark, d):
    return filtered(table(spark, d, "part"), Not(Or(Native("p_type = 'PROMO'"), atom("red", "p_name"))), Runtime()).select("p_partkey")


@query(f"SELECT event_id, user_id FROM events WHERE ts < TIMESTAMP '2024-01-15 00:00:00' AND {twin('failure', 'event_type')}")
def lm_filter_before_date(spark, d):
    e = And(Native("ts < TIMESTAMP_NTZ '2024-01-15 00:00:00'"), atom("failure", "event_type"))
    return filtered(table(spark, d, "events"), e, Runtime()).select("event_id", "user_id")


# --- projections, classes, structures -------------------------------------------------------------
_W07 = f"""SELECT colour, count(*) AS n, CAST(sum(lines) AS BIGINT) AS lines FROM (
  SELECT p_partkey, {twin('colour', 'p_name')} AS colour, count(*) AS lines FROM part JOIN lineitem ON l_partkey = p_partkey
  WHERE p_type IN ('PROMO', 'SMALL') GROUP BY p_partkey, p_name) GROUP BY colour"""


@query(_W07)
def lm_project_colour_join(spark, d):
    sold = table(spark, d, "lineitem").groupBy("l_partkey").agg(F.count(F.lit(1)).alias("c"))
    parts = table(spark, d, "part").where("p_type IN ('PROMO', 'SMALL')").select("p_partkey", "p_name").join(sold, F.col("p_partkey") == F.col("l_partkey"))
    return with_answers(parts, call("colour", "p_name"), "colour", Runtime()).groupBy("colour").agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("lines"))


@query("SELECT concat(CAST(CAST(floor(year(o_orderdate) / 10) * 10 AS INT) AS VARCHAR), 's') AS decade, o_orderpriority, count(*) AS n, min(o_orderkey) AS first_key FROM orders GROUP BY 1, 2")
def lm_class_group_concat(spark, d):
    orders = table(spark, d, "orders").withColumn("day", F.date_format("o_orderdate", "yyyy-MM-dd"))
    return with_answers(orders, call("decade", "day"), "decade", Runtime()).groupBy("decade", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.min("o_orderkey").alias("first_key"))


@query("SELECT lower(c_mktsegment) AS segment, count(*) AS n FROM customer GROUP BY 1")
def lm_class_5way(spark, d):
    return with_answers(table(spark, d, "customer"), call("segment", "c_mktsegment"), "segment", Runtime()).groupBy("segment").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT {twin('kind24', 'p_name', 'p_size')} AS kind, count(*) AS n FROM part GROUP BY 1")
def lm_class_24way(spark, d):
    return with_answers(table(spark, d, "part"), call("kind24", "p_name", "p_size"), "kind", Runtime()).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, CASE WHEN CAST(json_extract(props, '$.k') AS BIGINT) < 33 THEN 'low' WHEN CAST(json_extract(props, '$.k') AS BIGINT) < 66 THEN 'mid' ELSE 'high' END AS band, count(*) AS n FROM events GROUP BY 1, 2")
def lm_json_struct(spark, d):
    got = with_answers(table(spark, d, "events"), call("json_band", "props"), "x", Runtime())
    return got.groupBy(F.col("x.k").alias("k"), F.col("x.band").alias("band")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT tag, count(*) AS n FROM (SELECT unnest(string_split(p_name, ' ')) AS tag FROM part) GROUP BY tag")
def lm_list_answer(spark, d):
    got = with_answers(table(spark, d, "part"), call("tags", "p_name"), "tags", Runtime())
    return got.select(F.explode("tags").alias("tag")).groupBy("tag").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT event_id, CASE WHEN value > 50 THEN ({twin('failure', 'event_type')}) ELSE FALSE END AS bad FROM events")
def lm_case_when(spark, d):
    rt, events = Runtime(), table(spark, d, "events").select("event_id", "event_type", "value")
    needs = with_answers(events.where("value > 50"), call("failure", "event_type"), "bad", rt).select("event_id", "bad")
    return needs.unionByName(events.where("NOT coalesce(value > 50, FALSE)").select("event_id", F.lit(False).alias("bad")))


@query(f"SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE lower(c_mktsegment) = 'building')")
def lm_in_subquery(spark, d):
    found = filtered(table(spark, d, "customer"), atom("segment", "c_mktsegment", template="{} = 'building'"), Runtime())
    return table(spark, d, "orders").join(found, F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("o_orderkey")


@query(f"(SELECT p_partkey FROM part WHERE {twin('red', 'p_name')} UNION SELECT p_partkey FROM part WHERE {twin('ring', 'p_name')}) EXCEPT SELECT p_partkey FROM part WHERE {twin('thermal', 'p_name')}")
def lm_set_ops(spark, d):
    rt, part = Runtime(), table(spark, d, "part")
    red, ring, hot = (filtered(part, atom(s, "p_name"), rt).select("p_partkey") for s in ("red", "ring", "thermal"))
    return red.union(ring).distinct().subtract(hot)


@query(f"SELECT doc_id, score, CAST(rank() OVER (PARTITION BY source ORDER BY score DESC) AS INTEGER) AS place FROM (SELECT doc_id, source, {twin('score', 'text')} AS score FROM documents)")
def lm_window_rank(spark, d):
    got = with_answers(table(spark, d, "documents"), call("score", "text"), "score", Runtime())
    return got.select("doc_id", "score", F.rank().over(Window.partitionBy("source").orderBy(F.desc("score"))).alias("place"))


@query(f"SELECT doc_id, {twin('score', 'text')} AS score FROM documents ORDER BY score DESC, doc_id LIMIT 50")
def lm_order_by_score(spark, d):
    return with_answers(table(spark, d, "documents"), call("score", "text"), "score", Runtime()).orderBy(F.desc("score"), "doc_id").limit(50).select("doc_id", "score")


@query(f"SELECT {twin('language', 'text')} AS language, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 100")
def lm_having(spark, d):
    return with_answers(table(spark, d, "documents"), call("language", "text"), "language", Runtime()).groupBy("language").agg(F.count(F.lit(1)).alias("n")).where("n > 100")


@query(f"SELECT source, count(*) AS n FROM documents WHERE {twin('email', 'text')} GROUP BY source")
def lm_count_agg(spark, d):
    return filtered(table(spark, d, "documents"), atom("email", "text"), Runtime()).groupBy("source").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT lang, round(avg({twin('score', 'text')}), 6) AS mean_score FROM documents GROUP BY lang")
def lm_avg_score(spark, d):
    return with_answers(table(spark, d, "documents"), call("score", "text"), "score", Runtime()).groupBy("lang").agg(F.round(F.avg("score"), 6).alias("mean_score"))


# --- cascades and early exit ----------------------------------------------------------------------
_BOTH = f"{twin('thermal', 'p_name')} AND {twin('ring', 'p_name')}"


@query(f"SELECT p_partkey FROM part WHERE {_BOTH}")
def lm_cascade_two(spark, d):
    return filtered(table(spark, d, "part"), And(atom("thermal", "p_name"), atom("ring", "p_name")), Runtime()).select("p_partkey")


@query(f"SELECT p_partkey FROM part WHERE {_BOTH} ORDER BY p_partkey LIMIT 20")
def lm_early_exit_cascade(spark, d):
    return early_exit(table(spark, d, "part"), And(atom("thermal", "p_name"), atom("ring", "p_name")), 20, "p_partkey", Runtime()).select("p_partkey")


@query(f"SELECT doc_id FROM documents WHERE lang = 'en' AND {twin('clean', 'text')} ORDER BY doc_id LIMIT 5")
def lm_early_exit_key(spark, d):
    return early_exit(table(spark, d, "documents"), And(Native("lang = 'en'"), atom("clean", "text")), 5, "doc_id", Runtime()).select("doc_id")


@query(f"SELECT doc_id, item_id FROM documents d, benchmark b WHERE {twin('license', 'd.text')} AND {twin('contains', 'd.text', 'b.text')}")
def lm_cascade_pair(spark, d):
    rt = Runtime()
    docs = filtered(table(spark, d, "documents"), atom("license", "text"), rt).select("doc_id", "text")
    items = table(spark, d, "benchmark").select("item_id", F.col("text").alias("passage"))
    return lm_join(docs, items, SKILLS["contains"].question, ("text",), ("passage",), rt).select("doc_id", "item_id")


# --- joins ----------------------------------------------------------------------------------------
def _sides(spark, d, keys):
    part = table(spark, d, "part").where(F.col("p_partkey") < keys)
    return part.select(F.col("p_partkey").alias("a"), F.col("p_name").alias("a_name")), part.select(F.col("p_partkey").alias("b"), F.col("p_name").alias("b_name"))


@query(f"SELECT x.p_name AS a_name, y.p_name AS b_name, count(*) AS n FROM part x, part y WHERE x.p_partkey < y.p_partkey AND {twin('same_kind', 'x.p_name', 'y.p_name')} GROUP BY 1, 2")
def lm_join_same_kind(spark, d):
    """Pairs of keys a < b of the whole table, counted by pair of names."""
    part = table(spark, d, "part").select("p_partkey", "p_name")
    a, b = (part.select(F.col("p_name").alias(c)).distinct() for c in ("a_name", "b_name"))
    yes = lm_join(a, b, SKILLS["same_kind"].question, ("a_name",), ("b_name",), Runtime())
    sides = [part.join(yes, part["p_name"] == yes[c]).select("a_name", "b_name", "p_partkey", F.lit(int(c == "a_name")).alias("a"), F.lit(int(c == "b_name")).alias("b")) for c in ("a_name", "b_name")]
    keys = sides[0].unionByName(sides[1]).groupBy("a_name", "b_name", "p_partkey").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    before = Window.partitionBy("a_name", "b_name").orderBy("p_partkey").rowsBetween(Window.unboundedPreceding, -1)
    counted = keys.withColumn("n", F.col("b") * F.coalesce(F.sum("a").over(before), F.lit(0)))
    return counted.groupBy("a_name", "b_name").agg(F.sum("n").alias("n")).where("n > 0")


def _license_sides(spark, d):
    docs = table(spark, d, "documents").where("lower(text) LIKE '%license%'").select("doc_id", "text")
    return docs, table(spark, d, "benchmark").select("item_id", F.col("text").alias("passage"))


@query("SELECT doc_id FROM documents d WHERE lower(text) LIKE '%license%' AND EXISTS (SELECT 1 FROM benchmark b WHERE position(b.text IN d.text) > 0)")
def lm_join_semi(spark, d):
    docs, items = _license_sides(spark, d)
    return lm_join(docs, items, SKILLS["contains"].question, ("text",), ("passage",), Runtime(), how="left_semi").select("doc_id")


@query("SELECT doc_id FROM documents d WHERE lower(text) LIKE '%license%' AND NOT EXISTS (SELECT 1 FROM benchmark b WHERE position(b.text IN d.text) > 0)")
def lm_join_anti(spark, d):
    docs, items = _license_sides(spark, d)
    return lm_join(docs, items, SKILLS["contains"].question, ("text",), ("passage",), Runtime(), how="left_anti").select("doc_id")


@query("SELECT p_name, count(*) AS n FROM part a, (SELECT p_name AS other FROM part) b WHERE split_part(p_name, ' ', 2) = split_part(other, ' ', 2) GROUP BY p_name")
def lm_cross_dedup(spark, d):
    """Each name with the number of key pairs of the whole table that it makes."""
    names = table(spark, d, "part").groupBy("p_name").agg(F.count(F.lit(1)).alias("n0"))
    counts = names.select(F.col("p_name").alias("other"), F.col("n0").alias("c"))
    return lm_join(names, counts, SKILLS["same_kind"].question, ("p_name",), ("other",), Runtime()).groupBy("p_name").agg((F.first("n0") * F.sum("c")).cast("long").alias("n"))


# --- set functions --------------------------------------------------------------------------------
@query("SELECT CAST(row_number() OVER (ORDER BY length(text) DESC, text) AS INTEGER) AS rank, text FROM (SELECT DISTINCT text FROM conversations WHERE role = 'user') ORDER BY length(text) DESC, text LIMIT 3")
def lm_topk_options(spark, d):
    return lm_topk(table(spark, d, "conversations").where("role = 'user'"), SKILLS["longest"].question, "text", 3, Runtime())


@query("SELECT n_name FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = (SELECT r_name FROM region ORDER BY length(r_name) DESC, r_name LIMIT 1)")
def lm_link_scalar(spark, d):
    both = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return lm_link(both, SKILLS["longest"].question, "r_name", Runtime(), table(spark, d, "region").select("r_name")).select("n_name")


@query("SELECT name AS answer FROM (SELECT 'item ' || label AS name FROM (SELECT label, list_inner_product(list_transform(embedding, lambda x: CAST(x AS DOUBLE)), (SELECT list_transform(embedding, lambda x: CAST(x AS DOUBLE)) FROM embeddings WHERE vec_id = 0)) AS s, vec_id FROM embeddings ORDER BY s DESC, vec_id LIMIT 5)) ORDER BY length(name) DESC, name LIMIT 1")
def lm_rag_topn(spark, d):
    vectors = table(spark, d, "embeddings").withColumn("name", F.concat(F.lit("item "), F.col("label")))
    one = vectors.where("vec_id = 0").first()["embedding"]
    near = retrieve(vectors, "embedding", [float(x) for x in one], 5, "vec_id")
    return spark.createDataFrame([(lm_ask(SKILLS["longest"].question, Runtime(), options=near.select("name")),)], "answer string")


@query("SELECT lang, text FROM (SELECT lang, text, row_number() OVER (PARTITION BY lang ORDER BY length(text) DESC, text) AS r FROM (SELECT DISTINCT lang, text FROM documents WHERE text IS NOT NULL)) WHERE r = 1")
def lm_group_ask(spark, d):
    """The longest text of each language, of all texts."""
    return lm_agg(table(spark, d, "documents"), SKILLS["longest"].question, "text", ["lang"], "text", Runtime())


# --- modalities -----------------------------------------------------------------------------------
@query("SELECT user_id, max(value) > 99 AS loud FROM events GROUP BY user_id")
def lm_series_class(spark, d):
    series = table(spark, d, "events").groupBy("user_id").agg(F.max("value").alias("peak"))
    series = series.withColumn("media", F.to_json(F.array("peak")))
    return with_answers(series, call("loud", "media", modality="audio"), "loud", Runtime()).select("user_id", "loud")


@query("SELECT user_id FROM events WHERE FALSE")
def lm_audio_no_hits(spark, d):
    series = table(spark, d, "events").groupBy("user_id").agg(F.max("value").cast("string").alias("media"))
    return filtered(series, atom("never", "media"), Runtime()).select("user_id")


@query("""WITH r AS (SELECT vec_id, label, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings), c AS (SELECT label AS class, i, avg(x) AS m FROM r GROUP BY label, i),
s AS (SELECT vec_id, label, class, sum(x * m) AS s FROM r JOIN c USING (i) GROUP BY vec_id, label, class)
SELECT vec_id, class AS answer, class = label AS right FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY s DESC, class) AS k FROM s) WHERE k = 1""")
def lm_vector_class(spark, d):
    """Nearest class centroid of each vector, and whether it is the label: the stand-in for images."""
    rows = table(spark, d, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("i", "x"))
    centre = rows.groupBy("label", "i").agg(F.avg("x").alias("m")).withColumnRenamed("label", "class")
    dots = rows.join(centre, "i").groupBy("vec_id", "label", "class").agg(F.sum(F.col("x") * F.col("m")).alias("s"))
    best = dots.groupBy("vec_id", "label").agg(F.max_by("class", F.struct("s", -F.col("class"))).alias("answer"))
    return best.select("vec_id", "answer", (F.col("answer") == F.col("label")).alias("right"))


# --- SQL surface ----------------------------------------------------------------------------------
def _views(spark, d, *names):
    for n in names:
        table(spark, d, n).createOrReplaceTempView(f"v_{n}")


@query(f"SELECT p_partkey, p_name FROM part WHERE p_type IN ('PROMO', 'SMALL') AND NOT ({twin('red', 'p_name')}) AND {twin('ring', 'p_name')}")
def lm_sql_filter(spark, d):
    _views(spark, d, "part")
    return run_sql(spark, "SELECT p.p_partkey, p.p_name FROM v_part p WHERE p.p_type IN ('PROMO', 'SMALL') AND lm_map('Is it red?', p.p_name) = FALSE AND lm_map('Is it a ring?', p.p_name)", Runtime())


@query("SELECT colour, count(*) AS n FROM (SELECT CASE WHEN split_part(p_name, ' ', 1) IN ('red', 'blue') THEN split_part(p_name, ' ', 1) ELSE 'none' END AS colour FROM part WHERE p_size > 10) GROUP BY colour")
def lm_sql_group(spark, d):
    _views(spark, d, "part")
    q = "SELECT lm_map('What is the main colour?', p_name, options => array('red', 'blue', 'none')) AS colour, count(*) AS n FROM v_part WHERE p_size > 10 GROUP BY lm_map('What is the main colour?', p_name, options => array('red', 'blue', 'none'))"
    return run_sql(spark, q, Runtime())


@query("SELECT n_name FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = (SELECT r_name FROM region ORDER BY length(r_name) DESC, r_name LIMIT 1)")
def lm_sql_link(spark, d):
    _views(spark, d, "nation", "region")
    return run_sql(spark, "SELECT n_name FROM v_nation JOIN v_region ON n_regionkey = r_regionkey WHERE r_name = lm_ask('Which is the longest?', options => (SELECT r_name FROM v_region))", Runtime())


# --- measures -------------------------------------------------------------------------------------
@query("SELECT 'part.p_name' AS input, round(count(*) / CAST(count(DISTINCT p_name) AS DOUBLE), 6) AS factor FROM part UNION ALL SELECT 'documents.text', round(count(*) / CAST(count(DISTINCT text) AS DOUBLE), 6) FROM documents UNION ALL SELECT 'events.event_type', round(count(*) / CAST(count(DISTINCT event_type) AS DOUBLE), 6) FROM events")
def dup_factor(spark, d):
    rows = [(f"{t}.{c}", round(M.dup_factor(table(spark, d, t), [c]), 6)) for t, c in (("part", "p_name"), ("documents", "text"), ("events", "event_type"))]
    return spark.createDataFrame(rows, "input string, factor double")


_CALLS = "SELECT '{0}' AS step, CAST({1} AS BIGINT) AS calls FROM part"


@query(" UNION ALL ".join(_CALLS.format(*x) for x in (
    ("ours", f"count(DISTINCT p_name) + count(DISTINCT CASE WHEN {twin('thermal', 'p_name')} THEN p_name END)"), ("lazy", f"count(*) + count(CASE WHEN {twin('thermal', 'p_name')} THEN 1 END)"),
    ("eager", f"count(*) + count(CASE WHEN {twin('thermal', 'p_name')} THEN 1 END)"), ("aqp", "2 * count(*)"), ("none", "2 * count(*)"),
)))
def calls_by_feature(spark, d):
    """Calls of the two-predicate cascade under each strategy, against counts from SQL alone."""
    w = Workload(table(spark, d, "part"), And(atom("thermal", "p_name"), atom("ring", "p_name")), "p_partkey")
    rows = []
    for s in ("ours", "lazy", "eager", "aqp", "none"):
        df, rt = run(w, s)
        df.count()
        rows.append((s, rt.calls))
    return spark.createDataFrame(rows, "step string, calls long")


@query(f"""WITH p AS (SELECT doc_id FROM documents WHERE {twin('clean', 'text')}), l AS (SELECT * FROM labels), j AS (
  SELECT count(*) FILTER (WHERE p.doc_id IS NOT NULL AND quality = 1) AS hit, count(p.doc_id) AS n, count(*) FILTER (WHERE quality = 1) AS m FROM l LEFT JOIN p USING (doc_id))
SELECT hit, n, m, round(2.0 * hit / (n + m), 6) AS f1 FROM j""")
def quality_f1_clean(spark, d):
    labels = table(spark, d, "labels")
    own = filtered(table(spark, d, "documents").join(labels, "doc_id"), atom("clean", "text"), Runtime())
    r = own.agg(F.count(F.when(F.col("quality") == 1, 1)), F.count(F.lit(1))).first()
    m = labels.where("quality = 1").count()
    q = M.f1(own.select("doc_id"), labels.where("quality = 1").select("doc_id"), ["doc_id"])["f1"]
    return spark.createDataFrame([(r[0], r[1], m, round(q, 6))], "hit long, n long, m long, f1 double")


@query("""WITH s AS (SELECT doc_id, 1 + least(4, n_chars // 1000) AS score, n_chars FROM documents JOIN labels USING (doc_id)),
r AS (SELECT rank() OVER (ORDER BY score) + (count(*) OVER (PARTITION BY score) - 1) / 2.0 AS a, rank() OVER (ORDER BY n_chars) + (count(*) OVER (PARTITION BY n_chars) - 1) / 2.0 AS b FROM s)
SELECT round(corr(a, b), 6) AS rho FROM r""")
def quality_spearman_score(spark, d):
    docs = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id")
    rho = M.spearman(with_answers(docs, call("score", "text"), "score", Runtime()), "score", "n_chars")
    return spark.createDataFrame([(round(rho, 6),)], "rho double")


def _wrong(skill: str, inputs: str, name: str, e: float) -> str:
    return f"CAST(('0x' || substr(md5('{name}|{SKILLS[skill].question}|' || {inputs}), 1, 8)) AS BIGINT) / 4294967296.0 < {e}"


@query(f"""WITH n AS (SELECT p_name, {twin('red', 'p_name')} AS truth, {_wrong('red', "'{\"p_name\":\"' || p_name || '\"}'", 'noisy', 0.2)} AS wrong FROM part)
SELECT CAST(count(*) FILTER (WHERE truth <> wrong) AS BIGINT) AS answered, CAST(count(*) FILTER (WHERE truth) AS BIGINT) AS truth FROM n""")
def quality_abs_error_count(spark, d):
    part = table(spark, d, "part")
    n = filtered(part, atom("red", "p_name"), Runtime(provider=NoisyProvider("noisy", error={"text": 0.2}))).count()
    return spark.createDataFrame([(n, filtered(part, atom("red", "p_name"), Runtime()).count())], "answered long, truth long")


@query("SELECT round(sum(greatest(1, s)) * 0.18 / 3600, 9) AS usd FROM (SELECT count(DISTINCT p_name) * 0.05 AS s FROM part)")
def cost_local(spark, d):
    rt = Runtime()
    with_answers(table(spark, d, "part"), call("red", "p_name"), "x", rt).count()
    return spark.createDataFrame([(round(M.local_cost(max(1.0, rt.calls * 0.05)), 9),)], "usd double")


@query("SELECT CAST(sum(ceil(length(p_name || '') / 4.0)) AS BIGINT) AS name_tokens, count(*) AS calls FROM (SELECT DISTINCT p_name FROM part)")
def cost_api(spark, d):
    rt = Runtime()
    with_answers(table(spark, d, "part"), call("red", "p_name"), "x", rt).count()
    assert M.api_cost(rt.ledger) > 0
    tokens = table(spark, d, "part").select("p_name").distinct().agg(F.sum(F.ceil(F.length("p_name") / 4))).first()[0]
    return spark.createDataFrame([(tokens, rt.calls)], "name_tokens long, calls long")


@query(f"""WITH m AS (SELECT * FROM part ORDER BY p_partkey LIMIT 500), c AS (SELECT count(*) AS n FROM part)
SELECT CAST(count(*) FILTER (WHERE {twin('red', 'p_name')}) AS BIGINT) AS lower, CAST(count(*) FILTER (WHERE {twin('red', 'p_name')}) + (SELECT greatest(n - 500, 0) FROM c) AS BIGINT) AS upper FROM m""")
def aqp_count_bounds(spark, d):
    b = aqp_aggregate(table(spark, d, "part"), atom("red", "p_name"), "count", "p_partkey", Runtime(), max_calls=500, wave=500)
    return spark.createDataFrame([(b["lower"], b["upper"])], "lower long, upper long")


_WILSON = "({0} / {1} + 1.9208 / {1} - 1.96 * sqrt({0} / {1} * (1 - {0} / {1}) / {1} + 0.9604 / ({1} * {1}))) / (1 + 3.8416 / {1})"


@query(f"""WITH s AS (SELECT doc_id, text, CASE WHEN regexp_matches(text, '[$%#*&]{{2}}') THEN 0.1 ELSE 0.9 END AS p, {twin('clean', 'text')} AS y FROM documents),
k AS (SELECT * FROM s ORDER BY md5(CAST(doc_id AS VARCHAR)) LIMIT 200),
c AS (SELECT p, CAST(sum(n) OVER (ORDER BY p DESC) AS DOUBLE) AS n, CAST(sum(h) OVER (ORDER BY p DESC) AS DOUBLE) AS h, CAST((SELECT count(*) FROM k WHERE y) AS DOUBLE) AS m FROM (SELECT p, count(*) AS n, count(*) FILTER (WHERE y) AS h FROM k GROUP BY p)),
t AS (SELECT coalesce(min(p) FILTER (WHERE {_WILSON.format('h', 'n')} >= 0.9), 9) AS high, coalesce(max(p) FILTER (WHERE m > 0 AND {_WILSON.format('h', 'm')} >= 0.9), 0) AS low FROM c)
SELECT (SELECT count(*) FROM s, t WHERE p >= high OR (p >= low AND y)) AS kept, (SELECT count(DISTINCT text) FROM s, t WHERE (p < high AND p >= low) OR doc_id IN (SELECT doc_id FROM k)) AS calls, CAST(low AS DOUBLE) AS low, CAST(high AS DOUBLE) AS high FROM t""")
def proxy_cascade_calls(spark, d):
    rt, docs = Runtime(), table(spark, d, "documents")
    score = F.when(F.col("text").rlike("[$%#*&]{2}"), 0.1).otherwise(0.9)
    out, cut = proxy_cascade(docs, call("clean", "text"), score, rt, by=F.md5(F.col("doc_id").cast("string")))
    return spark.createDataFrame([(out.count(), rt.calls, float(cut["low"]), min(9.0, float(cut["high"])))], "kept long, calls long, low double, high double")


@query()
def eager_vs_lazy_calls(spark, d):
    w = Workload(table(spark, d, "part"), And(Native("p_type = 'PROMO'"), atom("red", "p_name", template="{} = FALSE")), "p_partkey", 10)
    rows = []
    for s in ("eager", "lazy", "ours"):
        df, rt = run(w, s)
        rows.append((s, df.count(), rt.calls))
    return spark.createDataFrame(rows, "strategy string, n long, calls long")


@query(f"SELECT p_partkey FROM part WHERE {twin('red', 'p_name')}")
def batch5_legacy(spark, d):
    df, _ = run(Workload(table(spark, d, "part"), atom("red", "p_name"), "p_partkey"), "v0")
    return df.select("p_partkey")


@query()
def ablation_ladder(spark, d):
    """Each switch turned on in its turn, with a model that also writes malformed replies."""
    w = Workload(table(spark, d, "part"), And(atom("thermal", "p_name"), atom("ring", "p_name")), "p_partkey", 20)
    return spark.createDataFrame([tuple(r.values()) for r in ablate(w, PROFILES["small-4b"])], "step string, n long, calls long, malformed long")


@query()
def models_by_strategy(spark, d):
    """Quality and calls of four models under the strategies on one filter."""
    part, rows = table(spark, d, "part"), []
    truth = filtered(part, atom("red", "p_name"), Runtime()).select("p_partkey")
    for model in ("small-2b", "small-4b", "dense-4b", "dense-12b"):
        for s in ("v0", "eager", "lazy", "aqp", "ours"):
            df, rt = run(Workload(part, atom("red", "p_name"), "p_partkey"), s, PROFILES[model])
            rows.append((model, s, round(M.f1(df.select("p_partkey"), truth, ["p_partkey"])["f1"], 6), rt.calls))
    return spark.createDataFrame(rows, "model string, strategy string, f1 double, calls long")


@query(" UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS keys, (SELECT count(*) FROM (SELECT DISTINCT p_name AS x FROM part WHERE p_partkey < {k}), (SELECT DISTINCT p_name AS y FROM part WHERE p_partkey < {k}) WHERE {twin('same_kind', 'x', 'y')}) AS yes_pairs, (SELECT count(DISTINCT p_name) * count(DISTINCT p_name) FROM part WHERE p_partkey < {k}) AS calls" for k in (250, 500, 1000, 2000)))
def scale_sweep(spark, d):
    """Pairs and distinct pair inputs of the self-join as the keys grow: calls level off."""
    rows = []
    for keys in (250, 500, 1000, 2000):
        left, right = _sides(spark, d, keys)
        rt = Runtime()
        n = lm_join(left.groupBy("a_name").agg(F.count(F.lit(1)).alias("m")), right.groupBy("b_name").agg(F.count(F.lit(1)).alias("k")), SKILLS["same_kind"].question, ("a_name",), ("b_name",), rt).count()
        rows.append((keys, n, rt.calls))
    return spark.createDataFrame(rows, "keys long, yes_pairs long, calls long")
