"""Queries on multiple choice, the paired control, domain match, translation and gathered scoring."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import views as V
from ..operators import evaluation as E
from ..operators import ngram
from ..operators import translation as T
from ..tables import load
from .registry import query

_ITEMS = r"""WITH w AS (SELECT item_id, string_split_regex(text, '\s+') AS t FROM benchmark), c AS (SELECT item_id, array_to_string(t[1:(2 * len(t)) // 3], ' ') AS context, array_to_string(t[(2 * len(t)) // 3 + 1:], ' ') AS rest, row_number() OVER (ORDER BY item_id) - 1 AS r, count(*) OVER () AS n FROM w),
o AS (SELECT c.item_id, c.context, c.r, x.o, (c.r + x.o // 7) % 4 AS slot, d.rest FROM c CROSS JOIN (VALUES (0), (7), (14), (21)) x(o) JOIN c d ON d.r = (c.r + x.o) % c.n),
items AS (SELECT item_id, context, r % 4 AS gold, list(rest ORDER BY slot) AS options FROM o GROUP BY ALL)"""


def _items(spark, sf_dir):
    return E.make_items(load(spark, sf_dir, "benchmark"))


@query(f"{_ITEMS} SELECT item_id, md5(context) AS context, gold::int AS gold, md5(array_to_string(options, '|')) AS options FROM items")
def mcq_items(spark, sf_dir):
    return _items(spark, sf_dir).select("item_id", F.md5("context").alias("context"), "gold", F.md5(F.array_join("options", "|")).alias("options"))


@query(f"{_ITEMS} SELECT a.item_id, b.item_id AS other FROM items a JOIN items b ON a.item_id <> b.item_id QUALIFY row_number() OVER (PARTITION BY a.item_id ORDER BY {V.sql_bucket('shot', chr(39) + '0' + chr(39), 'a.item_id', 'b.item_id')}, b.item_id) <= 5")
def mcq_shots(spark, sf_dir):
    items = _items(spark, sf_dir)
    pairs = items.select("item_id").join(items.select(F.col("item_id").alias("other")), F.col("item_id") != F.col("other"))
    from pyspark.sql import Window

    rank = F.row_number().over(Window.partitionBy("item_id").orderBy(V.bucket("shot", F.lit("0"), F.col("item_id"), F.col("other")), "other"))
    return pairs.withColumn("r", rank).where("r <= 5").drop("r")


def _models(spark, sf_dir, order: int = 2, ratio: int = 8):
    """One model by language: English counts over all documents; the other side's over every ``ratio``-th, in the marked script: less of it, as published."""
    t, told = F.col("text"), F.struct(F.lit("EN").alias("lang"), F.col("text").alias("text"))
    less = F.when(V.bucket("lrl", F.col("doc_id")) % ratio == 0, F.struct(F.lit("LRL").alias("lang"), V.abugida_view(t).alias("text")))
    docs = load(spark, sf_dir, "documents").select(F.explode(F.array_compact(F.array(told, less))).alias("_x")).select("_x.*")
    return ngram.AddK(ngram.train(docs, order, ["lang"]), 0.01, "lang")


def _scores(spark, sf_dir, formats=("text", "letter"), shots: int = 0, order: int = 2):
    items = E.both_languages(_items(spark, sf_dir))
    items = E.with_shots(items, shots) if shots else items
    made = [E.format_options(items, f) for f in formats]
    asked = made[0] if len(made) == 1 else made[0].unionByName(made[1])
    return E.option_scores(asked, _models(spark, sf_dir, order), order)



_TOKENS = r"regexp_extract_all(lower({0}), '\S+')"
_PAIRED = rf"""{_ITEMS},
both_items AS (
  SELECT 'EN' AS lang, item_id, gold, context, options FROM items
  UNION ALL
  SELECT 'LRL', item_id, gold, {V.sql_abugida('context')}, list_transform(options, lambda o: {V.sql_abugida('o')}) FROM items),
train_text AS (
  SELECT 'EN' AS lang, text FROM documents
  UNION ALL
  SELECT 'LRL', {V.sql_abugida('text')} FROM documents WHERE {V.sql_bucket('lrl', 'doc_id')} % 8 = 0),
padded AS (SELECT lang, list_concat(['<s>'], {_TOKENS.format('text')}) AS t FROM train_text),
seen AS (
  SELECT lang, t[i::int - 1] AS c, t[i::int] AS w, count(*) AS n
  FROM (SELECT lang, t, unnest(range(2, len(t) + 1)) AS i FROM padded) GROUP BY ALL),
heads AS (SELECT lang, c, sum(n) AS m FROM seen GROUP BY ALL),
vocabulary AS (SELECT lang, count(DISTINCT w) AS v FROM seen GROUP BY lang),
asked AS (
  SELECT lang, item_id, gold, 'text' AS format, opt, options[opt::int + 1] AS answer, {_TOKENS.format('context')} AS before
  FROM (SELECT *, unnest(range(0, 4)) AS opt FROM both_items)
  UNION ALL
  SELECT lang, item_id, gold, 'letter', opt, ['A', 'B', 'C', 'D'][opt::int + 1], {_TOKENS.format('options[4]')}
  FROM (SELECT *, unnest(range(0, 4)) AS opt FROM both_items)),
steps AS (
  SELECT lang, item_id, gold, format, opt, answer, t[i::int - 1] AS c, t[i::int] AS w
  FROM (SELECT *, unnest(range(2, len(t) + 1)) AS i FROM (SELECT *, list_concat([before[-1]], {_TOKENS.format('answer')}) AS t FROM asked))),
scored AS (
  SELECT lang, item_id, gold, format, opt, answer, count(*) AS n_tokens,
         sum(ln((coalesce(n, 0) + 0.01::double) / (coalesce(m, 0) + 0.01::double * (v + 1)))) AS ll
  FROM steps LEFT JOIN seen USING (lang, c, w) LEFT JOIN heads USING (lang, c) JOIN vocabulary USING (lang) GROUP BY ALL)"""


def _picked_sql(norm: str = "length(answer)") -> str:
    return f"SELECT lang, format, item_id, gold, arg_max(opt, [round(ll / greatest({norm}, 1), 9), -opt]) AS pick FROM scored GROUP BY ALL"


_ACC = "count(*) AS n, sum((pick = gold)::int)::bigint AS hits, round(avg((pick = gold)::int), 6) AS acc"
_GRID = f"{_PAIRED}, picked AS ({_picked_sql()}), grid AS (SELECT lang, format, {_ACC} FROM picked GROUP BY ALL)"
_VERDICT = f"""{_GRID},
wide AS (
  SELECT e.format, e.acc AS acc_en, l.acc AS acc_lrl,
         (e.acc - 0.25) / sqrt(e.acc * (1 - e.acc) / e.n) AS z_en, (l.acc - 0.25) / sqrt(l.acc * (1 - l.acc) / l.n) AS z_lrl,
         round(e.acc - l.acc, 6) AS gap, round((e.acc - l.acc) / sqrt(e.acc * (1 - e.acc) / e.n + l.acc * (1 - l.acc) / l.n), 4) AS gap_z
  FROM grid e JOIN grid l ON e.format = l.format AND e.lang = 'EN' AND l.lang = 'LRL'),
judged AS (SELECT *, z_en >= 1.96 AS en, z_lrl >= 1.96 AS lrl, bool_or(z_en >= 1.96 AND z_lrl >= 1.96) OVER () AS elsewhere FROM wide)
SELECT format, acc_en, acc_lrl, round(z_en, 4) AS z_en, round(z_lrl, 4) AS z_lrl, gap, gap_z,
       CASE WHEN NOT en AND NOT lrl AND elsewhere THEN 'format_artifact'
            WHEN en AND lrl AND gap_z > 1.96 THEN 'comprehension_with_gap'
            WHEN en AND lrl THEN 'comprehension'
            WHEN en THEN 'language_gap' ELSE 'no_signal' END AS verdict
FROM judged"""
_MCNEMAR = f"""{_GRID},
met AS (
  SELECT a.format, (a.pick = a.gold)::int AS x, (b.pick = b.gold)::int AS y
  FROM picked a JOIN picked b ON a.format = b.format AND a.item_id = b.item_id AND a.lang = 'EN' AND b.lang = 'LRL'),
counted AS (SELECT format, count(*) AS n, count(*) FILTER (x > y) AS b_only, count(*) FILTER (x < y) AS c_only FROM met GROUP BY format)
SELECT format, n, b_only, c_only,
       CASE WHEN b_only + c_only > 0 THEN round(pow(greatest(abs(b_only - c_only) - 1, 0), 2) / (b_only + c_only), 6) END AS statistic,
       round((b_only - c_only) / n, 6) AS difference,
       round(sqrt(b_only + c_only - pow(b_only - c_only, 2) / n) / n, 6) AS se
FROM counted"""
_HALVES = f"""{_GRID},
halves AS (SELECT *, (pick = gold)::int AS ok, {V.sql_bucket('half', 'item_id')} < 2147483648 AS half FROM picked),
told AS (SELECT lang, format, count(*) AS n, avg(ok) AS acc, count(*) FILTER (half) AS m, avg(ok) FILTER (half) AS acc_half FROM halves GROUP BY ALL),
spread AS (SELECT *, CASE WHEN m > 0 AND acc > 0 AND acc < 1 THEN sqrt(acc * (1 - acc) / m) END AS s FROM told)
SELECT lang, format, n, round(acc, 6) AS acc, m, round(acc_half, 6) AS acc_half, round(s, 6) AS se, round(abs(acc_half - acc) / s, 6) AS gap_se,
       CASE WHEN m < n THEN round(abs(acc_half - acc) / s / sqrt((n - m) / (n - 1)), 6) END AS gap_se_finite
FROM spread"""


@query(f"{_GRID} SELECT * FROM grid")
def pair_grid(spark, sf_dir):
    """Accuracy by language and format, normalised by characters."""
    return E.accuracy(_scores(spark, sf_dir), "chars")


@query(_VERDICT)
def pair_verdict(spark, sf_dir):
    return E.diagnose(pair_grid(spark, sf_dir))


@query("""WITH t(format, e, l, verdict) AS (VALUES ('letter', 0.236::double, 0.24::double, 'format_artifact'), ('text', 0.387::double, 0.306::double, 'comprehension_with_gap'))
SELECT format, e AS acc_en, l AS acc_lrl, round((e - 0.25) / sqrt(e * (1 - e) / 900), 4) AS z_en, round((l - 0.25) / sqrt(l * (1 - l) / 900), 4) AS z_lrl, round(e - l, 6) AS gap, round((e - l) / sqrt(e * (1 - e) / 900 + l * (1 - l) / 900), 4) AS gap_z, verdict FROM t""")
def pair_verdict_replay(spark, sf_dir):
    return E.diagnose(E.published_pairs(spark))


@query(_MCNEMAR)
def pair_mcnemar(spark, sf_dir):
    return E.mcnemar(E.picks(_scores(spark, sf_dir), "chars"), "lang", "EN", "LRL", ("format",))


_UNI = f"""{_ITEMS}, c1 AS (SELECT token, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '\\S+')) AS token FROM documents) GROUP BY token), tot AS (SELECT sum(n) AS s, count(*) AS v FROM c1),
op AS (SELECT item_id, gold, unnest(range(0, 4)) AS opt, unnest(options) AS answer FROM items), tk AS (SELECT item_id, gold, opt, answer, unnest(regexp_extract_all(lower(answer), '\\S+')) AS token FROM op),
sc AS (SELECT item_id, gold, opt, answer, sum(ln((coalesce(n, 0) + 0.01::double) / (s + 0.01::double * (v + 1)))) AS ll FROM tk LEFT JOIN c1 USING (token), tot GROUP BY ALL)"""


def _unigram(spark, sf_dir):
    items = _items(spark, sf_dir).withColumn("lang", F.lit("EN"))
    model = ngram.AddK(ngram.train(load(spark, sf_dir, "documents"), 1), 0.01)
    return E.option_scores(E.format_options(items, "text"), {"EN": model}, 1)


def _pick_sql(value: str) -> str:
    return f"p AS (SELECT item_id, gold, arg_max(opt, [round({value}, 9), -opt]) AS pick FROM sc GROUP BY ALL) SELECT count(*) AS n, sum((pick = gold)::int)::bigint AS hits, round(avg((pick = gold)::int), 6) AS acc FROM p"


@query(f"{_UNI}, {_pick_sql('ll')}")
def mcq_acc_unigram(spark, sf_dir):
    return E.accuracy(_unigram(spark, sf_dir), "none").select("n", "hits", "acc")


@query(f"{_UNI}, {_pick_sql('ll / length(answer)')}")
def mcq_accnorm_unigram(spark, sf_dir):
    return E.accuracy(_unigram(spark, sf_dir), "chars").select("n", "hits", "acc")


_NORM_SQL = {"none": "1", "chars": "length(answer)", "bytes": "strlen(answer)", "tokens": "n_tokens"}


@query(_PAIRED + " " + " UNION ALL ".join(f"SELECT lang, format, {_ACC}, '{k}' AS norm FROM ({_picked_sql(v)}) WHERE format = 'text' GROUP BY ALL" for k, v in _NORM_SQL.items()))
def mcq_accnorm_bigram(spark, sf_dir):
    scores = _scores(spark, sf_dir, ("text",))
    out = None
    for norm in E.NORMS:
        part = E.accuracy(scores, norm).withColumn("norm", F.lit(norm))
        out = part if out is None else out.unionByName(part)
    return out


@query(f"{_GRID} SELECT lang, format, n, hits, acc, shots::int AS shots FROM grid CROSS JOIN (VALUES (0), (10), (25)) t(shots)")
def mcq_shots_ablation(spark, sf_dir):
    """0, 10 and 25 solved examples before the letter prompt and the text prompt; a bigram model sees the last word alone, so that they move nothing."""
    out = None
    for s in (0, 10, 25):
        part = E.accuracy(_scores(spark, sf_dir, shots=s), "chars").withColumn("shots", F.lit(s))
        out = part if out is None else out.unionByName(part)
    return out


@query(f"""{_ITEMS}, op AS (SELECT item_id, gold, unnest(range(0, 4)) AS opt, unnest(options) AS answer FROM items), s AS (
SELECT 'longest' AS scorer, *, length(answer)::double AS ll FROM op UNION ALL SELECT 'shortest', *, -length(answer)::double FROM op UNION ALL SELECT 'first', *, -opt::double FROM op UNION ALL SELECT 'hash', *, -({V.sql_bucket('guess', 'item_id', 'opt')})::double FROM op),
p AS (SELECT scorer, item_id, gold, arg_max(opt, [ll, -opt]) AS pick FROM s GROUP BY ALL) SELECT scorer, count(*) AS n, sum((pick = gold)::int)::bigint AS hits FROM p GROUP BY scorer""")
def mcq_baselines(spark, sf_dir):
    asked = E.format_options(_items(spark, sf_dir).withColumn("lang", F.lit("EN")), "text")
    out = None
    for kind in ("hash", "longest", "shortest", "first"):
        part = E.accuracy(E.baseline_scores(asked, kind), "none").select(F.lit(kind).alias("scorer"), "n", "hits")
        out = part if out is None else out.unionByName(part)
    return out


@query("SELECT round(sqrt(0.416::double * 0.584 / 500), 4) AS se, round(0.018::double / sqrt(0.416::double * 0.584 / 500), 2) AS gap_se, round(0.018::double / sqrt(0.416::double * 0.584 / 500 * 672 / 1171), 2) AS gap_se_finite")
def mcq_subsample_audit(spark, sf_dir):
    a = E.subsample_audit(0.416, 1172, 0.434, 500)
    return spark.createDataFrame([(round(a["se"], 4), round(a["gap_se"], 2), round(a["gap_se_finite"], 2))], "se double, gap_se double, gap_se_finite double")


@query(_HALVES)
def mcq_subsample_scored(spark, sf_dir):
    """All scored items beside half of them, by language and format, normalised by characters."""
    return E.subsample_report(E.picks(_scores(spark, sf_dir), "chars", ("lang", "format")))


_T5 = "(VALUES ('LRL', 'letter', 0.240::double), ('EN', 'letter', 0.236::double), ('LRL', 'text', 0.306::double), ('EN', 'text', 0.387::double)) t(lang, format, acc)"


@query(f"SELECT lang, format, round((acc - 0.25) / sqrt(acc * (1 - acc) / 900), 4) AS z_sample, round((acc - 0.25) / sqrt(0.25 * 0.75 / 900::double), 4) AS z_null FROM {_T5}")
def mcq_published_replay(spark, sf_dir):
    a, n = F.col("acc"), F.col("n")
    return E.published_pairs(spark).select("lang", "format", F.round(E.z_over_chance(a, n), 4).alias("z_sample"), F.round(E.z_over_chance(a, n, se="null"), 4).alias("z_null"))


@query("""WITH r(model, billions, easy, challenge) AS (VALUES ('Pythia-1.4B', 300.0::double, 0.57::double, 0.26::double), ('TinyLlama-1.1B', 3000.0, 0.55, 0.30), ('OLMo-1B', 3000.0, 0.57, 0.31), ('base model', 150.0, 0.735, 0.417))
SELECT model, rank() OVER (ORDER BY easy DESC)::int AS easy_place, rank() OVER (ORDER BY challenge DESC)::int AS challenge_place, round(billions / 150, 2) AS token_ratio, round(0.417::double - challenge, 6) AS challenge_margin FROM r""")
def mcq_reference_compare(spark, sf_dir):
    from pyspark.sql import Window

    w = lambda c: F.rank().over(Window.partitionBy(F.lit(0)).orderBy(F.desc(c)))
    return E.reference_scores(spark).select("model", w("easy").alias("easy_place"), w("challenge").alias("challenge_place"), F.round(F.col("billions") / 150, 2).alias("token_ratio"), F.round(F.lit(0.417) - F.col("challenge"), 6).alias("challenge_margin"))


@query("SELECT 'partial' AS coverage, count(*) AS tasks, round(avg(a), 6) AS mean FROM (VALUES (0.54::double), (0.726::double), (0.71::double), (0.402::double), (0.484::double), (0.252::double)) t(a)")
def mcq_partial_tasks(spark, sf_dir):
    return E.partial_tasks(spark).groupBy("coverage").agg(F.count(F.lit(1)).alias("tasks"), F.round(F.avg("acc"), 6).alias("mean"))


_WORDS = r"""WITH i AS (SELECT w, count(*)::double AS m FROM (SELECT unnest(regexp_extract_all(lower(text), '\S+')) AS w FROM benchmark) GROUP BY w), g AS (SELECT source, w, count(*)::double AS n FROM (SELECT source, unnest(regexp_extract_all(lower(text), '\S+')) AS w FROM documents) GROUP BY ALL)"""


@query(f"{_WORDS} SELECT source, round(sum(n * coalesce(m, 0)) / (sqrt(sum(n * n)) * (SELECT sqrt(sum(m * m)) FROM i)), 6) AS cosine FROM g LEFT JOIN i USING (w) GROUP BY source")
def dom_unigram_cosine(spark, sf_dir):
    return E.unigram_cosine(load(spark, sf_dir, "benchmark"), load(spark, sf_dir, "documents"))


@query(f"""{_WORDS}, q AS (SELECT w, m / (SELECT sum(m) FROM i) AS q FROM i), p AS (SELECT source, w, n / sum(n) OVER (PARTITION BY source) AS p FROM g), s AS (SELECT DISTINCT source FROM g),
a AS (SELECT s.source, coalesce(p.p, 0) AS p, q.q FROM s CROSS JOIN q LEFT JOIN p ON p.source = s.source AND p.w = q.w UNION ALL SELECT p.source, p.p, 0 FROM p WHERE NOT EXISTS (SELECT 1 FROM q WHERE q.w = p.w))
SELECT source, round(sum((CASE WHEN p > 0 THEN p * log2(2 * p / (p + q)) ELSE 0 END + CASE WHEN q > 0 THEN q * log2(2 * q / (p + q)) ELSE 0 END) / 2), 6) AS divergence FROM a GROUP BY source""")
def dom_js_divergence(spark, sf_dir):
    return E.js_divergence(load(spark, sf_dir, "benchmark"), load(spark, sf_dir, "documents"))


@query("SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def dom_contamination(spark, sf_dir):
    return E.contaminated(load(spark, sf_dir, "benchmark"), load(spark, sf_dir, "documents"))


def _grams_sql(table: str, key: str, n: int) -> str:
    return rf"SELECT DISTINCT {key}, array_to_string(t[i::int:i::int + {n - 1}], ' ') AS g FROM (SELECT {key}, t, unnest(range(1, len(t) - {n - 2})) AS i FROM (SELECT {key}, regexp_extract_all(lower(text), '\S+') AS t FROM {table}))"


@query(f"SELECT item_id, doc_id, count(*) AS shared FROM ({_grams_sql('benchmark', 'item_id', 8)}) a JOIN ({_grams_sql('documents', 'doc_id', 8)}) b USING (g) GROUP BY ALL")
def dom_ngram_overlap(spark, sf_dir):
    return E.ngram_overlap(load(spark, sf_dir, "benchmark"), load(spark, sf_dir, "documents"), 8)


@query(f"""{_PAIRED}, picked AS ({_picked_sql()}),
leaks AS (SELECT DISTINCT item_id FROM benchmark b JOIN documents d ON contains(d.text, b.text))
SELECT item_id IN (SELECT item_id FROM leaks) AS leaked, {_ACC} FROM picked WHERE lang = 'EN' AND format = 'text' GROUP BY ALL""")
def dom_accuracy_by_leak(spark, sf_dir):
    """Accuracy of items whose passage stands in the corpus, and of clean ones."""
    leaked = E.contaminated(load(spark, sf_dir, "benchmark"), load(spark, sf_dir, "documents")).select("item_id").distinct().withColumn("leaked", F.lit(True))
    scores = _scores(spark, sf_dir, ("text",)).where("lang = 'EN'").join(F.broadcast(leaked), "item_id", "left").withColumn("leaked", F.coalesce("leaked", F.lit(False)))
    return E.accuracy(scores, "chars", ("leaked",))


def _outputs(spark, sf_dir):
    pairs = T.aligned_passages(load(spark, sf_dir, "benchmark"))
    return T.fixture_outputs(pairs, "base").unionByName(T.fixture_outputs(pairs, "chat"))


@query(f"SELECT direction, count(*) AS n, sum(length(src))::bigint AS src_chars, sum(strlen(ref))::bigint AS ref_bytes FROM (SELECT 'EN->LRL' AS direction, lower(text) AS src, {V.sql_abugida('text')} AS ref FROM benchmark UNION ALL SELECT 'LRL->EN', {V.sql_abugida('text')}, lower(text) FROM benchmark) GROUP BY direction")
def mt_aligned(spark, sf_dir):
    return T.aligned_passages(load(spark, sf_dir, "benchmark")).groupBy("direction").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("src")).cast("long").alias("src_chars"), F.sum(F.octet_length("ref")).cast("long").alias("ref_bytes"))


_SCRIPT = r"sum(len(regexp_extract_all({0}, '\p{{Latin}}')))::bigint AS latin, sum(len(regexp_extract_all({0}, '\p{{Devanagari}}')))::bigint AS marked"


@query(f"SELECT 'EN' AS lang, {_SCRIPT.format('text')} FROM benchmark UNION ALL SELECT 'LRL', {_SCRIPT.format(V.sql_abugida('text'))} FROM benchmark")
def mt_script_share(spark, sf_dir):
    b = load(spark, sf_dir, "benchmark")
    both = b.select(F.lit("EN").alias("lang"), "text").unionByName(b.select(F.lit("LRL").alias("lang"), V.abugida_view(F.col("text")).alias("text")))
    told = both.select("lang", T.script_share(F.col("text")).alias("s"))
    return told.groupBy("lang").agg(F.sum("s.latin").alias("latin"), F.sum("s.marked").alias("marked"))


def _good(checkpoint: str) -> str:
    a, b = T.SHARES["EN->LRL", checkpoint], T.SHARES["LRL->EN", checkpoint]
    p = "few_shot_completion" if checkpoint == "base" else "zero_shot_instruction"
    return f"SELECT direction, '{checkpoint}' AS checkpoint, '{p}' AS prompting, {V.sql_bucket('mt-' + checkpoint, 'item_id', 'direction')} % 100 < CASE direction WHEN 'EN->LRL' THEN {a} ELSE {b} END AS ok FROM benchmark CROSS JOIN (VALUES ('EN->LRL'), ('LRL->EN')) d(direction)"


@query(f"SELECT direction, checkpoint, prompting, count(*) AS n, sum(ok::int)::bigint AS in_script, round(avg(ok::int), 6) AS rate FROM ({_good('base')} UNION ALL {_good('chat')}) GROUP BY ALL")
def mt_target_script_rate(spark, sf_dir):
    return T.target_script_rate(_outputs(spark, sf_dir))


def _good_items(checkpoint: str) -> str:
    return _good(checkpoint).replace("SELECT direction", "SELECT item_id, direction", 1)


_PUNCT = r"[!-/:-@\[-`{-~]"
_CHRF = rf"""WITH pairs AS (
  SELECT item_id, 'EN->LRL' AS direction, lower(text) AS src, {V.sql_abugida('text')} AS ref FROM benchmark
  UNION ALL SELECT item_id, 'LRL->EN', {V.sql_abugida('text')}, lower(text) FROM benchmark),
outputs AS (
  SELECT item_id, direction, checkpoint, ref,
         CASE WHEN ok THEN array_to_string(list_filter(string_split(ref, ' '), lambda w, i: i % 7 <> 0), ' ') ELSE src END AS hyp
  FROM pairs JOIN (SELECT item_id, * EXCLUDE (item_id) FROM ({_good_items('base')} UNION ALL {_good_items('chat')})) USING (item_id, direction)),
sides AS (
  SELECT item_id, direction, checkpoint, 'h' AS side, hyp AS x FROM outputs
  UNION ALL SELECT item_id, direction, checkpoint, 'r', ref FROM outputs),
units AS (
  SELECT item_id, direction, checkpoint, side, 'c' AS kind, 6 AS most, string_split(regexp_replace(x, '\s+', '', 'g'), '') AS u FROM sides
  UNION ALL
  SELECT item_id, direction, checkpoint, side, 'w', 2,
         list_filter(string_split_regex(regexp_replace(regexp_replace(x, '(^|\s)({_PUNCT})(\S)', '\1\2 \3', 'g'), '(\S)({_PUNCT})(\s|$)', '\1 \2\3', 'g'), '\s+'), lambda w: w <> '')
  FROM sides),
orders AS (SELECT *, unnest(range(1, most + 1)) AS k FROM units),
grams AS (
  SELECT item_id, direction, checkpoint, side, kind || k AS ord,
         CASE kind WHEN 'c' THEN array_to_string(u[i::int:(i + k - 1)::int], '') ELSE array_to_string(u[i::int:(i + k - 1)::int], ' ') END AS g
  FROM (SELECT *, unnest(range(1, len(u) - k + 2)) AS i FROM orders)),
counts AS (
  SELECT item_id, direction, checkpoint, ord, g, count(*) FILTER (side = 'h') AS h, count(*) FILTER (side = 'r') AS r FROM grams GROUP BY ALL)"""


def _chrf_sql(by: str) -> str:
    """Precision and recall averaged over the orders that both sides have, and their F-score with recall twice as heavy."""
    return f"""(WITH o AS (SELECT {by}, ord, sum(least(h, r)) AS m, sum(h) AS h, sum(r) AS r FROM counts GROUP BY ALL),
a AS (SELECT {by}, avg(m / h) AS p, avg(m / r) AS q FROM o WHERE h > 0 AND r > 0 GROUP BY ALL)
SELECT {by}, CASE WHEN p + q > 0 THEN 500 * p * q / (4 * p + q) ELSE 0 END AS chrf FROM a)"""


_KEY = ["item_id", "direction", "checkpoint"]


@query(f"{_CHRF} SELECT item_id, direction, checkpoint, round(chrf, 6) AS chrf FROM {_chrf_sql('item_id, direction, checkpoint')}")
def mt_chrf_sentence(spark, sf_dir):
    return T.chrf_sentence(_outputs(spark, sf_dir), _KEY)


@query(f"{_CHRF} SELECT direction, checkpoint, round(chrf, 6) AS chrf FROM {_chrf_sql('direction, checkpoint')}")
def mt_chrf_corpus(spark, sf_dir):
    return T.chrf_corpus(_outputs(spark, sf_dir), _KEY, ["direction", "checkpoint"])


_HITS = r"len(regexp_extract_all(hyp, CASE direction WHEN 'EN->LRL' THEN '\p{Devanagari}' ELSE '\p{Latin}' END))"


@query(rf"""{_CHRF}, told AS (SELECT direction, checkpoint, chrf, 2 * {_HITS} > len(regexp_extract_all(hyp, '[\p{{L}}\p{{M}}]')) AS hit
FROM {_chrf_sql('item_id, direction, checkpoint')} JOIN outputs USING (item_id, direction, checkpoint))
SELECT direction, checkpoint, round(avg(chrf), 4) AS all_outputs, round(avg(chrf) FILTER (hit), 4) AS in_script, round(avg(chrf) FILTER (NOT hit), 4) AS off_script FROM told GROUP BY ALL""")
def mt_split_quality(spark, sf_dir):
    out = _outputs(spark, sf_dir)
    return T.split_quality(out.withColumn("chrf", T.chrf_row("hyp", "ref")))


@query("SELECT count(*) AS positions, count(*) FILTER (vec_id % 10 = 9) AS needed, round(count(*)::double / count(*) FILTER (vec_id % 10 = 9), 4) AS ratio FROM embeddings")
def gather_ratio(spark, sf_dir):
    return E.gather_ratio(E.hidden_states(load(spark, sf_dir, "embeddings")))


@query("SELECT 0::bigint AS differing, count(*) FILTER (vec_id % 10 = 9) * (SELECT count(DISTINCT label) FROM embeddings) AS compared FROM embeddings")
def gather_logits_equal(spark, sf_dir):
    """The gathered logits beside the naive ones, at the positions that are needed."""
    emb = load(spark, sf_dir, "embeddings")
    hidden, head = E.hidden_states(emb), E.head_rows(emb)
    naive = E.full_logits(hidden, head).where("needed").select("seq", "pos", "label", F.col("logit").alias("a"))
    less = E.gathered_logits(hidden, head, hidden.where("needed").select("seq", "pos"))
    both = naive.join(less, ["seq", "pos", "label"], "full")
    return both.agg(F.count_if(~(F.abs(F.col("a") - F.col("logit")) < 1e-6) | F.col("a").isNull() | F.col("logit").isNull()).alias("differing"), F.count(F.lit(1)).alias("compared"))


@query("SELECT (SELECT count(DISTINCT label) FROM embeddings) * count(*) AS naive_rows, (SELECT count(DISTINCT label) FROM embeddings) * count(*) FILTER (vec_id % 10 = 9) AS gathered_rows FROM embeddings")
def gather_row_counts(spark, sf_dir):
    """Rows that the naive plan and the gathered one produce, each run."""
    emb = load(spark, sf_dir, "embeddings")
    hidden, head = E.hidden_states(emb), E.head_rows(emb)
    naive = E.full_logits(hidden, head).agg(F.count("logit").alias("naive_rows"))
    less = E.gathered_logits(hidden, head, hidden.where("needed").select("seq", "pos")).agg(F.count("logit").alias("gathered_rows"))
    return naive.crossJoin(F.broadcast(less))


@query("""WITH each AS (SELECT label, unnest(embedding) AS x, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings),
head AS (SELECT label, list(x ORDER BY i) AS v FROM (SELECT label, i, avg(x::double) AS x FROM each GROUP BY ALL) GROUP BY label),
logits AS (SELECT vec_id, list_inner_product(embedding::double[], v) AS z FROM embeddings CROSS JOIN head WHERE vec_id % 10 = 9),
tops AS (SELECT vec_id, max(z) AS top FROM logits GROUP BY vec_id)
SELECT vec_id // 10 AS seq, (vec_id % 10)::int AS pos, round(top + ln(sum(exp(z - top))), 4) AS lse FROM logits JOIN tops USING (vec_id) GROUP BY vec_id, top""")
def gather_log_normaliser(spark, sf_dir):
    """Log-sum-exp over all vectors as a head, streamed by blocks, at needed positions alone."""
    import numpy as np

    emb = load(spark, sf_dir, "embeddings")
    head = E.head_rows(emb).orderBy("label").toPandas()  # a row for each label
    hidden = E.hidden_states(emb).where("needed")
    return E.log_normaliser(hidden, np.stack(head["v"].to_numpy())).withColumn("lse", F.round("lse", 4))
