"""Queries on instruction sets, the tool contract, safety and arithmetic."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import views as V
from ..operators import contract as C
from ..operators import sftset as S
from ..tables import load
from .registry import query


def _conv(spark, sf_dir):
    return load(spark, sf_dir, "conversations")


_TASKS = "['arithmetic', 'units', 'weather', 'currency', 'free_form']"
_TAG = f"""WITH u AS (SELECT conv_id, turn, text, {V.sql_bucket('cond', 'conv_id', 'turn')} AS h, {_TASKS}[({V.sql_bucket('task', 'conv_id', 'turn')} % 5 + 1)::int] AS task FROM conversations WHERE role = 'user'),
g AS (SELECT *, CASE WHEN h % 10 <= 3 THEN 'A' WHEN h % 10 <= 5 THEN 'B' WHEN h % 10 <= 7 THEN 'C' ELSE 'D' END AS drawn FROM u),
t AS (SELECT conv_id, turn, text, task, CASE WHEN task = 'free_form' AND drawn IN ('A', 'B') THEN 'C' ELSE drawn END AS condition, (2 + (h // 16) % 6)::int AS distractors FROM g)"""
_CAT = "cat(name, category) AS (VALUES " + ", ".join(f"('{n}', '{c}')" for n, c, _ in S.CATALOG) + ")"
_MAN = f"""{_TAG}, {_CAT}, d AS (SELECT t.*, name, row_number() OVER (PARTITION BY conv_id, turn ORDER BY md5(concat_ws('|', 'dist', conv_id, turn, name))) AS r FROM t JOIN cat ON category <> task WHERE condition <> 'D'),
m AS (SELECT conv_id, turn, condition, task, distractors, name, false AS called FROM d WHERE r <= distractors UNION ALL SELECT conv_id, turn, condition, task, distractors, name, true FROM t JOIN cat ON category = task WHERE condition = 'A')"""


@query("SELECT conv_id, count(*) AS n_turns, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id")
def sft_assemble(spark, sf_dir):
    return S.assemble(_conv(spark, sf_dir)).select("conv_id", "n_turns", F.array_join(F.transform("turns", lambda t: t["role"]), ">").alias("roles"))


@query("""WITH w AS (SELECT *, lag(role) OVER v AS b, lead(role) OVER v AS n FROM conversations WINDOW v AS (PARTITION BY conv_id ORDER BY turn))
SELECT conv_id, NOT bool_or(coalesce(role = b OR (role = 'system' AND b IS NOT NULL), false)) AS alternates, bool_or(n IS NULL AND role = 'user') AS ends_with_user, bool_or(role = 'system') AS has_system FROM w GROUP BY conv_id""")
def sft_turn_validity(spark, sf_dir):
    return S.validate_turns(_conv(spark, sf_dir))


@query("SELECT role, count(*) AS turns, sum(length(text))::bigint AS chars FROM conversations WHERE role <> 'system' GROUP BY role")
def sft_v1(spark, sf_dir):
    return S.build_set(_conv(spark, sf_dir), "v1").groupBy("role").agg(F.count(F.lit(1)).alias("turns"), F.sum(F.length("text")).cast("long").alias("chars"))


@query(f"""WITH n AS (SELECT count(*) AS n FROM conversations WHERE role <> 'system'), s AS (SELECT l.doc_id AS conv_id, 0 AS turn, text FROM labels l JOIN documents d ON l.doc_id = d.doc_id WHERE toxic = 1),
p AS (SELECT *, row_number() OVER (ORDER BY {V.sql_bucket('safety', 'conv_id', 'turn')}, conv_id, turn) AS r FROM s)
SELECT 'general' AS origin, n AS turns FROM n UNION ALL SELECT 'safety', count(*) FROM p, n WHERE r <= floor(n * 0.05::double / 0.95) GROUP BY 1""")
def sft_v2(spark, sf_dir):
    safety = load(spark, sf_dir, "labels").where("toxic = 1").join(load(spark, sf_dir, "documents"), "doc_id").select(F.col("doc_id").alias("conv_id"), F.lit(0).cast("long").alias("turn"), F.lit("user").alias("role"), "text")
    return S.build_set(_conv(spark, sf_dir), "v2", safety=safety, share=0.05).groupBy("origin").agg(F.count(F.lit(1)).alias("turns"))


@query(f"{_TAG} SELECT condition, task, count(*) AS n FROM t GROUP BY ALL")
def sft_v3_conditions(spark, sf_dir):
    return S.tag_turns(_conv(spark, sf_dir)).groupBy("condition", "task").agg(F.count(F.lit(1)).alias("n"))


@query(f"{_MAN} SELECT conv_id, turn, condition, string_agg(name, ',' ORDER BY md5(concat_ws('|', 'ord', conv_id, turn, name))) AS tools FROM m GROUP BY ALL")
def sft_manifests(spark, sf_dir):
    made = S.synthesize_manifest(S.tag_turns(_conv(spark, sf_dir))).where("manifest is not null")
    return made.select("conv_id", "turn", "condition", F.array_join(F.transform("manifest", lambda m: m["name"]), ",").alias("tools"))


@query(f"{_MAN}, k AS (SELECT conv_id, turn, condition, count(*) FILTER (NOT called) AS d, count(*) FILTER (called) AS c FROM m GROUP BY ALL) SELECT condition, min(d)::int AS fewest, max(d)::int AS most, sum(c)::bigint AS called FROM k GROUP BY condition")
def sft_manifest_bounds(spark, sf_dir):
    made = S.synthesize_manifest(S.tag_turns(_conv(spark, sf_dir))).where("manifest is not null")
    called = F.size(F.filter("manifest", lambda m: F.coalesce(m["name"] == F.col("tool"), F.lit(False))))
    told = made.withColumns({"c": called, "d": F.size("manifest") - called})
    return told.groupBy("condition").agg(F.min("d").alias("fewest"), F.max("d").alias("most"), F.sum("c").cast("long").alias("called"))


_ANS = f"{_TAG}, a AS (SELECT conv_id, turn, lead(text) OVER v AS answer, lead(role) OVER v AS r, role FROM conversations WINDOW v AS (PARTITION BY conv_id ORDER BY turn)), b AS (SELECT t.*, CASE WHEN r = 'assistant' THEN answer END AS answer FROM t LEFT JOIN a USING (conv_id, turn))"


@query(f"""{_ANS}, e AS (SELECT condition, CASE condition WHEN 'A' THEN '<call>' || CASE task {' '.join(f"WHEN '{c}' THEN '{n}'" for n, c, _ in S.CATALOG)} END WHEN 'B' THEN '{S.DECLINE['en']}' ELSE answer END AS x FROM b)
SELECT condition, count(*) AS n, sum(length(x))::bigint AS trained_chars FROM e WHERE x IS NOT NULL GROUP BY condition""")
def sft_loss_mask_share(spark, sf_dir):
    """Trained characters alone are compared with SQL; masked ones are checked in tests."""
    return S.masked_share(S.build_set(_conv(spark, sf_dir), "v3"), ["condition"]).drop("masked_chars")


@query("SELECT 0::bigint AS leaks")
def sft_manifest_leaks(spark, sf_dir):
    return S.manifest_leaks(S.build_set(_conv(spark, sf_dir), "v3")).agg(F.count(F.lit(1)).alias("leaks"))


@query(f"{_ANS} SELECT task, condition, count(*) AS n, grouping_id(task, condition)::int AS level FROM b WHERE condition IN ('A', 'B') OR answer IS NOT NULL GROUP BY CUBE (task, condition)")
def sft_mixture_cube(spark, sf_dir):
    return S.mixture_report(S.build_set(_conv(spark, sf_dir), "v3"))


_RESP = f"{_TAG}, r AS (SELECT condition, task, CASE WHEN conv_id % 2 = 0 THEN 'en' ELSE 'lrl' END AS lang, {V.sql_bucket('resp', 'conv_id', 'turn')} AS h FROM t)"
#: What the undertrained fixture system does over all turns: it misses calls of units, and in the other language calls a tool for some requests that want none.
_OBS = f"""{_RESP}, o AS (SELECT *, NOT ((condition = 'A' AND task = 'units') OR (condition = 'C' AND lang = 'lrl' AND h % 5 = 0)) AS ok FROM r),
acc AS (SELECT condition, sum(ok::int)::bigint AS passed, count(*) AS n FROM o GROUP BY condition)"""


def _observed(spark, sf_dir):
    return C.fixture_responder(S.synthesize_manifest(S.tag_turns(_conv(spark, sf_dir))), "undertrained")


@query(f"{_OBS} SELECT * FROM acc")
def ctr_acceptance_replay(spark, sf_dir):
    return C.acceptance(_observed(spark, sf_dir))


@query(f"""{_OBS}, x AS (SELECT CASE WHEN condition IN ('B', 'D') THEN 'permission' ELSE 'appropriateness' END AS half, ok FROM o)
SELECT coalesce(half, 'all') AS half, sum(ok::int)::bigint AS passed, count(*) AS n FROM x GROUP BY ROLLUP (half)""")
def ctr_halves(spark, sf_dir):
    return C.acceptance_halves(_observed(spark, sf_dir))


@query(f"""{_OBS} SELECT condition, round(greatest((p + zz / (2 * n)) / (1 + zz / n) - h, 0), 6) AS low, round(least((p + zz / (2 * n)) / (1 + zz / n) + h, 1), 6) AS high FROM (
SELECT condition, n, p, zz, 1.96::double * sqrt(p * (1 - p) / n + zz / (4 * n * n)) / (1 + zz / n) AS h FROM (SELECT condition, n, passed::double / n AS p, 1.96::double * 1.96 AS zz FROM acc))""")
def ctr_wilson(spark, sf_dir):
    low, high = C.wilson(F.col("passed"), F.col("n"))
    return C.acceptance(_observed(spark, sf_dir)).select("condition", F.round(low, 6).alias("low"), F.round(high, 6).alias("high"))


_TAIL = "list_sum(list_transform(range({0}, {1}), lambda k: exp(lgamma(n + 1) - lgamma(k + 1) - lgamma(n - k + 1) + k * ln({2}) + (n - k) * ln(1 - {2}))))"


@query(f"""{_OBS.replace("WITH", "WITH RECURSIVE", 1)},
bisect(step, condition, x, n, a, b, c, d) AS (
  SELECT 0, condition, passed, n, 0.0::double, 1.0::double, 0.0::double, 1.0::double FROM acc
  UNION ALL
  SELECT step + 1, condition, x, n,
         CASE WHEN {_TAIL.format('x', 'n + 1', '((a + b) / 2)')} < 0.025 THEN (a + b) / 2 ELSE a END,
         CASE WHEN {_TAIL.format('x', 'n + 1', '((a + b) / 2)')} < 0.025 THEN b ELSE (a + b) / 2 END,
         CASE WHEN x = n OR {_TAIL.format('0', 'x + 1', '((c + d) / 2)')} > 0.025 THEN (c + d) / 2 ELSE c END,
         CASE WHEN x = n OR {_TAIL.format('0', 'x + 1', '((c + d) / 2)')} > 0.025 THEN d ELSE (c + d) / 2 END
  FROM bisect WHERE step < 45)
SELECT condition, round(CASE WHEN x = 0 THEN 0 ELSE a END, 4) AS low, round(CASE WHEN x = n THEN 1 ELSE d END, 4) AS high FROM bisect WHERE step = 45""")
def ctr_exact_intervals(spark, sf_dir):
    return C.acceptance(_observed(spark, sf_dir)).withColumn("ci", C.exact_interval("passed", "n")).select("condition", F.round("ci.low", 4).alias("low"), F.round("ci.high", 4).alias("high"))


@query(f"{_OBS}, x AS (SELECT condition, task, lang, count(*) AS misses FROM o WHERE NOT ok GROUP BY ALL) SELECT *, round(misses / sum(misses) OVER (), 6) AS share FROM x")
def ctr_misses(spark, sf_dir):
    return C.miss_concentration(_observed(spark, sf_dir))


@query(f"{_TAG} SELECT conv_id * 1000 + turn AS probe, condition, task FROM t WHERE condition = 'C' AND {V.sql_bucket('resp', 'conv_id', 'turn')} % 5 = 0")
def ctr_language_divergence(spark, sf_dir):
    """Each turn asked in both languages of the undertrained fixture."""
    tagged = S.synthesize_manifest(S.tag_turns(_conv(spark, sf_dir)))
    sides = [C.fixture_responder(tagged, "undertrained", F.lit(lang)) for lang in ("en", "lrl")]
    return C.language_divergence(sides[0].unionByName(sides[1]))




@query(f"""{_RESP} SELECT 'always_call' AS responder, condition, sum(CASE WHEN condition = 'A' AND h % 7 <> 0 THEN 1 ELSE 0 END)::bigint AS passed, count(*) AS n FROM r GROUP BY condition
UNION ALL SELECT 'never_call', condition, sum(CASE WHEN condition <> 'A' THEN 1 ELSE 0 END)::bigint, count(*) FROM r GROUP BY condition UNION ALL SELECT 'oracle', condition, count(*), count(*) FROM r GROUP BY condition
UNION ALL SELECT 'undertrained', condition, sum(CASE WHEN (condition = 'A' AND task = 'units') OR (condition = 'C' AND lang = 'lrl' AND h % 5 = 0) THEN 0 ELSE 1 END)::bigint, count(*) FROM r GROUP BY condition
UNION ALL SELECT 'safety_heavy', condition, sum(CASE WHEN condition = 'A' AND h % 3 = 0 THEN 0 ELSE 1 END)::bigint, count(*) FROM r GROUP BY condition""")
def ctr_responders(spark, sf_dir):
    tagged = S.synthesize_manifest(S.tag_turns(_conv(spark, sf_dir)))
    out = None
    for kind in C.RESPONDERS:
        part = C.acceptance(C.fixture_responder(tagged, kind)).select(F.lit(kind).alias("responder"), "condition", "passed", "n")
        out = part if out is None else out.unionByName(part)
    return out


@query(f"{_RESP} SELECT 'invented' AS kind, count(*) AS n FROM r WHERE h % 7 = 0")
def ctr_invented_calls(spark, sf_dir):
    obs = C.fixture_responder(S.synthesize_manifest(S.tag_turns(_conv(spark, sf_dir))), "always_call")
    return C.invented_calls(obs, S.catalog_frame(spark)).where("kind = 'invented'").groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


_OKS = {
    "always_call": "condition = 'A' AND h % 7 <> 0",
    "never_call": "condition <> 'A'",
    "oracle": "true",
    "undertrained": "NOT ((condition = 'A' AND task = 'units') OR (condition = 'C' AND lang = 'lrl' AND h % 5 = 0))",
    "safety_heavy": "NOT (condition = 'A' AND h % 3 = 0)",
}
#: Each fixture system as a checkpoint: how much more often it rightly stays silent in English than in the other language, and its share of wanted calls.
_METRICS = f"""{_RESP}, k AS ({" UNION ALL ".join(f"SELECT '{k}' AS checkpoint, condition, lang, {ok} AS ok FROM r" for k, ok in _OKS.items())}),
m AS (SELECT checkpoint, round(avg(ok::int) FILTER (condition <> 'A' AND lang = 'en') - avg(ok::int) FILTER (condition <> 'A' AND lang = 'lrl'), 6) AS refusal_gap, round(avg(ok::int) FILTER (condition = 'A'), 6) AS tool_rate FROM k GROUP BY checkpoint)"""


def _metrics(spark, sf_dir):
    tagged = S.synthesize_manifest(S.tag_turns(_conv(spark, sf_dir)))
    out = None
    for kind in C.RESPONDERS:
        part = C.checkpoint_metrics(C.fixture_responder(tagged, kind)).withColumn("checkpoint", F.lit(kind))
        out = part if out is None else out.unionByName(part)
    return out


@query(f"""{_METRICS}
SELECT a.checkpoint, a.refusal_gap, a.tool_rate FROM m a WHERE NOT EXISTS (SELECT 1 FROM m b WHERE b.refusal_gap <= a.refusal_gap AND b.tool_rate >= a.tool_rate AND (b.refusal_gap < a.refusal_gap OR b.tool_rate > a.tool_rate))""")
def ctr_tradeoff_front(spark, sf_dir):
    return C.tradeoff_front(_metrics(spark, sf_dir)).select("checkpoint", "refusal_gap", "tool_rate")


@query(f"SELECT doc_id, lang, toxic FROM (SELECT doc_id, lang, toxic, row_number() OVER (PARTITION BY lang, toxic ORDER BY {V.sql_bucket('safe', 'doc_id')}, doc_id) AS r FROM labels JOIN documents USING (doc_id)) WHERE r <= 20")
def safe_prompts(spark, sf_dir):
    return C.safety_prompts(load(spark, sf_dir, "labels"), load(spark, sf_dir, "documents"))


_REF = f"{V.sql_bucket('refuse', 'doc_id')} % 100"


@query(f"""WITH o AS (SELECT CASE WHEN lang = 'en' THEN 'en' ELSE 'lrl' END AS lang, toxic = 1 AS harmful, CASE WHEN toxic = 1 AND lang = 'en' THEN {_REF} < 95 WHEN toxic = 1 THEN {_REF} < 60 ELSE {_REF} < 5 END AS refused FROM labels JOIN documents USING (doc_id)),
r AS (SELECT harmful, round(avg(refused::int) FILTER (lang = 'en'), 6) AS en, round(avg(refused::int) FILTER (lang = 'lrl'), 6) AS lrl FROM o GROUP BY harmful) SELECT *, round(en - lrl, 6) AS gap FROM r""")
def safe_refusal_gap(spark, sf_dir):
    """A fixture system that refuses harmful prompts less in the other languages than in English."""
    d = load(spark, sf_dir, "labels").join(load(spark, sf_dir, "documents").select("doc_id", "lang"), "doc_id")
    h, bad, en = V.bucket("refuse", F.col("doc_id")) % 100, F.col("toxic") == 1, F.col("lang") == "en"
    obs = d.select(F.when(en, "en").otherwise("lrl").alias("lang"), bad.alias("harmful"), F.when(bad & en, h < 95).when(bad, h < 60).otherwise(h < 5).alias("refused"))
    return C.refusal_gap(obs)


#: Requests on parts, of which the operands, the phrasing and the fixture system's answer are known without reading the text.
_PARTS = f"""WITH p AS (SELECT p_partkey AS probe, ['expression', 'word_problem', 'none'][(p_partkey % 3 + 1)::int] AS phrasing, coalesce(p_size, 0)::decimal(10, 0) AS size, coalesce(p_retailprice, 0)::decimal(18, 2) AS price,
{V.sql_bucket('manifest', 'p_partkey')} % 2 = 0 AS manifest, {V.sql_bucket('arith', 'p_partkey')} AS h FROM part),
c AS (SELECT *, phrasing <> 'none' AND manifest AND h % 5 <> 0 AS calls FROM p),
o AS (SELECT *, size * price AS truth, CASE WHEN phrasing = 'word_problem' AND NOT calls THEN CASE WHEN h % 3 = 0 THEN size * price ELSE size + price END END AS answered FROM c)"""


@query(f"""{_PARTS} SELECT phrasing, manifest, count(*) FILTER (calls) AS called, count(*) FILTER (NOT calls AND answered IS NULL) AS declined, count(answered) AS guessed, count(*) FILTER (answered <> truth) AS wrong FROM o GROUP BY phrasing, manifest""")
def arith_recognition(spark, sf_dir):
    return C.recognition_table(C.part_probes(load(spark, sf_dir, "part")))


@query(f"{_PARTS} SELECT probe, truth::double AS truth, answered::double AS answered, abs(truth::double - answered::double) AS error FROM o WHERE answered IS NOT NULL")
def arith_truth(spark, sf_dir):
    told = C.part_probes(load(spark, sf_dir, "part")).where("answered is not null").withColumn("truth", C.arith_truth(F.col("text")))
    return told.select("probe", F.col("truth").cast("double").alias("truth"), F.col("answered").cast("double").alias("answered"), F.abs(F.col("truth").cast("double") - F.col("answered").cast("double")).alias("error"))
