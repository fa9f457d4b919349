"""Queries on pools, mixtures, hold-out, language models and loss."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import views as V
from ..operators import dedup, ngram, pools
from ..tables import load
from .registry import query

_W = r"len(regexp_extract_all(text, '\S+'))"
_SIZES = f"count(*) AS docs, sum(length(text))::bigint AS chars, sum(strlen(text))::bigint AS bytes, sum({_W})::bigint AS words"


def _docs(spark, sf_dir):
    return load(spark, sf_dir, "documents")


@query(f"SELECT lang, source, {_SIZES} FROM documents GROUP BY lang, source")
def pool_table(spark, sf_dir):
    return pools.pool_table(_docs(spark, sf_dir))


@query(f"SELECT lang, source, grouping_id(lang, source)::int AS level, {_SIZES} FROM documents GROUP BY ROLLUP (lang, source)")
def pool_rollup(spark, sf_dir):
    return pools.pool_rollup(_docs(spark, sf_dir))


@query(f"SELECT lang, count(*) AS docs, sum(length(text))::bigint AS chars, sum({_W})::bigint AS words FROM (SELECT *, row_number() OVER (PARTITION BY text ORDER BY doc_id) AS r FROM documents) WHERE r = 1 GROUP BY lang")
def pool_unique(spark, sf_dir):
    return pools.unique_pool(_docs(spark, sf_dir))


@query("""WITH l AS (SELECT lang, text, list_filter(string_split(text, chr(10)), lambda x: length(x) > 0) AS ls FROM documents)
SELECT lang, count(*) AS docs, count(DISTINCT text) AS texts, sum(len(ls))::bigint AS lines, sum(len(ls) - len(list_distinct(ls)))::bigint AS repeated_lines FROM l GROUP BY lang""")
def pool_duplication(spark, sf_dir):
    return pools.duplication_report(_docs(spark, sf_dir))


@query()
def pool_near_dup(spark, sf_dir):
    """Sizes of the classes of near-duplicates (five words, similarity of 0.8 or more)."""
    classes = dedup.near_dup_clusters(_docs(spark, sf_dir))
    return classes.groupBy("cluster").agg(F.count(F.lit(1)).alias("docs")).where("docs > 1")


_POOLS = f"WITH p AS (SELECT lang AS pool, sum({_W})::bigint AS tokens FROM (SELECT *, row_number() OVER (PARTITION BY text ORDER BY doc_id) AS r FROM documents) WHERE r = 1 GROUP BY lang), e AS (SELECT 2.0 * tokens AS total FROM p WHERE pool = 'en')"


def _pools(spark, sf_dir):
    found = pools.unique_pool(_docs(spark, sf_dir)).select(F.col("lang").alias("pool"), F.col("words").alias("tokens"))
    return found, 2.0 * (found.where("pool = 'en'").first()["tokens"])


@query(f"{_POOLS}, w AS (SELECT pool, tokens, 0.25::double AS weight, 0.25 * total / tokens AS e FROM p, e) SELECT pool, tokens, weight, round(e, 6) AS epochs, CASE WHEN e < 1 THEN 'subsampled' WHEN e > 1 THEN 'repeated' ELSE 'once' END AS kind FROM w")
def mix_plan(spark, sf_dir):
    """Twice the English words in all, each language a quarter: the small pools are repeated."""
    found, total = _pools(spark, sf_dir)
    plan = pools.mixture_plan(pools.solve_weights(found, "fixed", shares={x: 0.25 for x in ("de", "en", "es", "fr")}), total)
    return plan.withColumn("epochs", F.round("epochs", 6))


@query(f"{_POOLS} SELECT pool, tokens, round(sqrt(tokens::double) / sum(sqrt(tokens::double)) OVER (), 9) AS half, round(tokens::double / sum(tokens) OVER (), 9) AS proportional FROM p")
def mix_temperature(spark, sf_dir):
    found, _ = _pools(spark, sf_dir)
    half = pools.solve_weights(found, "temperature", alpha=0.5)
    return pools.solve_weights(half.withColumnRenamed("weight", "half"), "proportional").select("pool", "tokens", F.round("half", 9).alias("half"), F.round("weight", 9).alias("proportional"))


@query(f"""{_POOLS}, c AS (SELECT pool, tokens, 4.0 * tokens / (3.0 * sum(tokens) OVER ()) AS cap FROM p),
levels AS (SELECT (1 - (SELECT coalesce(sum(cap), 0) FROM c x WHERE x.cap < c.cap)) / (SELECT count(*) FROM c x WHERE x.cap >= c.cap) AS level, cap FROM c),
u AS (SELECT max(level) AS level FROM levels),
w AS (SELECT pool, tokens, least(cap, u.level)::double AS weight, 3.0 * (SELECT sum(tokens) FROM p) AS total FROM c, u)
SELECT pool, tokens, round(weight, 9) AS weight, round(weight * total / tokens, 6) AS epochs,
       CASE WHEN weight * total / tokens < 1 THEN 'subsampled' WHEN weight * total / tokens > 1 THEN 'repeated' ELSE 'once' END AS kind FROM w""")
def mix_capped(spark, sf_dir):
    """Weights under a cap of four epochs, at three times all words."""
    found, _ = _pools(spark, sf_dir)
    total = 3.0 * found.agg(F.sum("tokens")).first()[0]
    plan = pools.mixture_plan(pools.solve_weights(found, "capped", alpha=0.0, total=total, max_epochs=4.0), total)
    return plan.withColumns({"weight": F.round("weight", 9), "epochs": F.round("epochs", 6)})


@query(f"""{_POOLS}, w AS (SELECT pool, 0.25 * total / tokens AS e FROM p, e), d AS (SELECT doc_id, lang, floor(e)::int + CASE WHEN {V.sql_bucket('mix', 'doc_id')} < (e - floor(e)) * 4294967296.0 THEN 1 ELSE 0 END AS n FROM documents JOIN w ON lang = pool)
SELECT lang, sum(n)::bigint AS copies, count(*) FILTER (n > 0) AS docs, max(n)::int AS most FROM d GROUP BY lang""")
def mix_sample(spark, sf_dir):
    found, total = _pools(spark, sf_dir)
    plan = pools.mixture_plan(pools.solve_weights(found, "fixed", shares={x: 0.25 for x in ("de", "en", "es", "fr")}), total).withColumnRenamed("pool", "lang")
    mixed = pools.sample_mixture(_docs(spark, sf_dir).select("doc_id", "lang"), plan, "lang")
    return mixed.groupBy("lang").agg(F.count(F.lit(1)).alias("copies"), F.countDistinct("doc_id").alias("docs"), F.max("epoch").alias("most"))


@query(f"{_POOLS} SELECT round(min(4.0 * tokens / 0.25), 4) AS max_tokens, min_by(pool, 4.0 * tokens / 0.25) AS binding FROM p")
def mix_ceiling(spark, sf_dir):
    found, _ = _pools(spark, sf_dir)
    weighted = pools.solve_weights(found, "fixed", shares={x: 0.25 for x in ("de", "en", "es", "fr")})
    return pools.data_ceiling(weighted, 4.0).withColumn("max_tokens", F.round("max_tokens", 4))


@query(f"{_POOLS} SELECT pool, b AS budget, round(b * 0.25 / tokens, 6) AS epochs FROM p, (VALUES (1e5::double), (1e6::double), (1e7::double)) t(b)")
def mix_whatif(spark, sf_dir):
    found, _ = _pools(spark, sf_dir)
    weighted = pools.solve_weights(found, "fixed", shares={x: 0.25 for x in ("de", "en", "es", "fr")})
    budgets = spark.createDataFrame([(1e5,), (1e6,), (1e7,)], "budget double")
    return pools.ceiling_whatif(weighted, budgets).select("pool", "budget", F.round("epochs", 6).alias("epochs"))


@query("SELECT count(*) AS docs, count(DISTINCT source) AS sources FROM documents WHERE source NOT IN ('src3', 'src7')")
def mix_release_filter(spark, sf_dir):
    return pools.release_filter(_docs(spark, sf_dir), ["src3", "src7"]).agg(F.count(F.lit(1)).alias("docs"), F.countDistinct("source").alias("sources"))


@query("""SELECT * FROM (VALUES ('published', 4.175::double, round(342 / 4.175::double, 2), round((342 + 12.8 + 1.7) / 4.175::double, 2))) t(pools, lrl_billions, web_ratio, all_ratio)""")
def mix_published_ratio(spark, sf_dir):
    """The published pools: the lower-resource side's sum and the ratios to it."""
    rows = [("web", "EN", 342.0), ("math", "EN", 12.8), ("code", "EN", 1.7), ("web", "LRL", 3.32), ("verified", "LRL", 0.40), ("news", "LRL", 0.42), ("encyclopedia", "LRL", 0.02), ("private", "LRL", 0.015)]
    p = spark.createDataFrame(rows, "pool string, side string, billions double")
    total = lambda c: F.sum(F.when(c, F.col("billions")))
    en, lrl = F.col("side") == "EN", F.col("side") == "LRL"
    return p.agg(F.lit("published").alias("pools"), F.round(total(lrl), 3).alias("lrl_billions"), F.round(total(en & (F.col("pool") == "web")) / total(lrl), 2).alias("web_ratio"), F.round(total(en) / total(lrl), 2).alias("all_ratio"))


_H = f"({V.sql_bucket('holdout', 'text')} % 100 < 10)"


@query(f"SELECT lang, {_H} AS held_out, count(*) AS docs FROM documents GROUP BY ALL")
def holdout_split(spark, sf_dir):
    return pools.split_holdout(_docs(spark, sf_dir)).groupBy("lang", "held_out").agg(F.count(F.lit(1)).alias("docs"))


_T = rf"list_concat(['<s>'], regexp_extract_all(lower(text), '\S+'))"


@query(r"""WITH t AS (SELECT lang, unnest(regexp_extract_all(lower(text), '\S+')) AS token FROM documents) SELECT lang, token, count(*) AS cnt FROM t GROUP BY ALL HAVING count(*) >= 20""")
def lm_unigram_counts(spark, sf_dir):
    return ngram.train(_docs(spark, sf_dir), 1, ["lang"]).where("cnt >= 20").drop("context")


@query(rf"""WITH t AS (SELECT {_T} AS t FROM documents), b AS (SELECT t[i::int - 1] AS context, t[i::int] AS token FROM (SELECT t, unnest(range(2, len(t) + 1)) AS i FROM t))
SELECT context, token, count(*) AS cnt FROM b GROUP BY ALL HAVING count(*) >= 10""")
def lm_bigram_counts(spark, sf_dir):
    return ngram.train(_docs(spark, sf_dir), 2).where("cnt >= 10")


_ROWS = "count(*) AS rows, sum(cnt)::bigint AS tokens, sum(cnt * cnt)::bigint AS squares, count(*) FILTER (cnt = 1) AS once"


def _all_counts(counts, *keys):
    """Sums over all counts, rare ones too."""
    c = F.col("cnt")
    return counts.groupBy(*keys).agg(F.count(F.lit(1)).alias("rows"), F.sum(c).alias("tokens"), F.sum(c * c).alias("squares"), F.count_if(c == 1).alias("once"))


@query(rf"""WITH t AS (SELECT lang, unnest(regexp_extract_all(lower(text), '\S+')) AS token FROM documents), c AS (SELECT lang, token, count(*) AS cnt FROM t GROUP BY ALL) SELECT lang, {_ROWS} FROM c GROUP BY lang""")
def lm_unigram_totals(spark, sf_dir):
    """What ``lm_unigram_counts`` leaves out is in here: all words of each language."""
    return _all_counts(ngram.train(_docs(spark, sf_dir), 1, ["lang"]), "lang")


@query(rf"""WITH t AS (SELECT lang, {_T} AS t FROM documents), b AS (SELECT lang, t[i::int - 1] AS context, t[i::int] AS token FROM (SELECT lang, t, unnest(range(2, len(t) + 1)) AS i FROM t)),
c AS (SELECT lang, context, token, count(*) AS cnt FROM b GROUP BY ALL) SELECT lang, {_ROWS} FROM c GROUP BY lang""")
def lm_bigram_totals(spark, sf_dir):
    """All word pairs of each language, those below the count of ``lm_bigram_counts`` too."""
    return _all_counts(ngram.train(_docs(spark, sf_dir), 2, ["lang"]), "lang")


_LM = rf"""WITH d AS (SELECT doc_id, lang, {_T} AS t, {_H} AS h FROM documents), b AS (SELECT doc_id, lang, h, t[i::int - 1] AS c, t[i::int] AS w FROM (SELECT doc_id, lang, h, t, unnest(range(2, len(t) + 1)) AS i FROM d)),
n AS (SELECT c, w, count(*) AS n FROM b WHERE NOT h GROUP BY ALL), m AS (SELECT c, sum(n) AS m FROM n GROUP BY c), v AS (SELECT count(DISTINCT w) AS v FROM n),
s AS (SELECT b.doc_id, b.lang, ln((coalesce(n.n, 0) + 0.1::double) / (coalesce(m.m, 0) + 0.1::double * (v.v + 1))) AS lp FROM b LEFT JOIN n ON b.c = n.c AND b.w = n.w LEFT JOIN m ON b.c = m.c, v WHERE b.h)"""


def _loss(spark, sf_dir, **sizes):
    """Held-out loss by language, ``ll`` and ``n_tokens``, with sums of ``sizes`` over the texts that have words."""
    docs = pools.split_holdout(_docs(spark, sf_dir).select("doc_id", "lang", "text"))
    held = docs.where("held_out")
    loss = ngram.score_groups(held, ngram.AddK(ngram.train(docs.where("not held_out"), 2), 0.1), 2, ["lang"])
    if not sizes:
        return loss
    words = held.where(F.col("text").rlike(r"\S"))
    return loss.join(words.groupBy("lang").agg(*[F.sum(c).alias(k) for k, c in sizes.items()]), "lang")


@query(f"{_LM} SELECT lang, count(*) AS tokens, round(-sum(lp) / count(*), 6) AS nats_per_token FROM s GROUP BY lang")
def lm_holdout_nll_addk(spark, sf_dir):
    return _loss(spark, sf_dir).select("lang", F.col("n_tokens").alias("tokens"), F.round(-F.col("ll") / F.col("n_tokens"), 6).alias("nats_per_token"))


_SMOOTHED = rf"""WITH d AS (SELECT {_T} AS t, {_H} AS h FROM documents),
b AS (SELECT h, t[i::int - 1] AS c, t[i::int] AS w FROM (SELECT h, t, unnest(range(2, len(t) + 1)) AS i FROM d)),
n AS (SELECT c, w, count(*) AS n FROM b WHERE NOT h GROUP BY ALL),
m AS (SELECT c, sum(n) AS m, count(*) AS types FROM n GROUP BY c),
u AS (SELECT w, sum(n) AS occurs, count(*) AS follows FROM n GROUP BY w),
z AS (SELECT sum(occurs)::double AS words, sum(follows)::double AS pairs, count(*) AS v FROM u),
s AS (
  SELECT coalesce(n, 0) AS n, m, types, v, (coalesce(occurs, 0) + 1) / (words + v + 1) AS p_word, (coalesce(follows, 0) + 1) / (pairs + v + 1) AS p_follow
  FROM b LEFT JOIN n USING (c, w) LEFT JOIN m USING (c) LEFT JOIN u USING (w), z WHERE h),
p AS (
  SELECT (n + 0.1::double) / (coalesce(m, 0) + 0.1::double * (v + 1)) AS add_k,
         CASE WHEN m IS NULL THEN p_word ELSE 0.5 * n / m + 0.5 * p_word END AS interpolated,
         CASE WHEN m IS NULL THEN p_word ELSE greatest(n - 0.75, 0) / m + 0.75 * types / m * p_word END AS absolute,
         CASE WHEN m IS NULL THEN p_follow ELSE greatest(n - 0.75, 0) / m + 0.75 * types / m * p_follow END AS kneser_ney
  FROM s)
SELECT smoothing, count(*) AS tokens, round(-avg(ln(p)), 6) AS nats_per_token FROM (UNPIVOT p ON add_k, interpolated, absolute, kneser_ney INTO NAME smoothing VALUE p) GROUP BY smoothing"""


@query(_SMOOTHED)
def lm_smoothing(spark, sf_dir):
    """Held-out loss of each smoothing, over the same counts."""
    docs = pools.split_holdout(_docs(spark, sf_dir).select("doc_id", "lang", "text"))
    train, test = docs.where("not held_out"), docs.where("held_out")
    two, one = ngram.train(train, 2), ngram.AddK(ngram.train(train, 1), 1.0)
    models = {"add_k": ngram.AddK(two, 0.1), "interpolated": ngram.Interpolated(two, one, 0.5), "absolute": ngram.KneserNey(two, 0.75, False), "kneser_ney": ngram.KneserNey(two, 0.75)}
    out = None
    for name, model in models.items():
        part = ngram.score(test, model, 2, ["doc_id"]).agg(F.lit(name).alias("smoothing"), F.sum("n_tokens").alias("tokens"), F.round(-F.sum("ll") / F.sum("n_tokens"), 6).alias("nats_per_token"))
        out = part if out is None else out.unionByName(part)
    return out


@query(f"{_LM}, l AS (SELECT doc_id, lang, sum(lp) AS ll FROM s GROUP BY ALL) SELECT l.lang, round(-sum(ll) / (ln(2) * sum(strlen(text))), 6) AS bits_per_byte FROM l JOIN documents USING (doc_id) GROUP BY l.lang")
def bpb_by_lang(spark, sf_dir):
    told = _loss(spark, sf_dir, n_bytes=F.octet_length("text"))
    return told.select("lang", F.round(ngram.bits_per_byte(-F.col("ll"), F.col("n_bytes")), 6).alias("bits_per_byte"))


@query(f"""{_LM}, l AS (SELECT doc_id, lang, sum(lp) AS ll FROM s GROUP BY ALL), j AS (SELECT l.lang, sum(ll) AS ll, sum(strlen(text)) AS b, sum(strlen({V.sql_abugida('text')})) AS m FROM l JOIN documents USING (doc_id) GROUP BY l.lang)
SELECT lang, round(-ll / (ln(2) * b), 6) AS latin, round(-ll / (ln(2) * m), 6) AS marked, round(m::double / b, 6) AS byte_ratio FROM j""")
def bpb_script_effect(spark, sf_dir):
    """One loss over two scripts: bits per byte fall by exactly the ratio of bytes."""
    by = _loss(spark, sf_dir, b=F.octet_length("text"), m=F.octet_length(V.abugida_view(F.col("text"))))
    return by.select("lang", F.round(ngram.bits_per_byte(-F.col("ll"), F.col("b")), 6).alias("latin"), F.round(ngram.bits_per_byte(-F.col("ll"), F.col("m")), 6).alias("marked"), F.round(F.col("m") / F.col("b"), 6).alias("byte_ratio"))


@query(rf"""{_LM}, l AS (SELECT doc_id, lang, sum(lp) AS ll, count(*) AS n FROM s GROUP BY ALL), j AS (SELECT l.lang, sum(ll) AS ll, sum(n) AS n, sum(strlen(text)) AS b, sum(length(text)) AS c, sum({_W}) AS w FROM l JOIN documents USING (doc_id) GROUP BY l.lang)
SELECT lang, round(-ll / (ln(2) * b), 6) AS bits_per_byte, round(-ll / ln(2) / c, 6) AS bits_per_char, round(-ll / n, 6) AS nats_per_token, round(-ll / w, 6) AS nats_per_word, round(exp(-ll / n), 2) AS perplexity FROM j""")
def loss_report(spark, sf_dir):
    t = F.col("text")
    told = _loss(spark, sf_dir, n_chars=F.length(t), n_bytes=F.octet_length(t), n_words=F.regexp_count(t, F.lit(r"\S+")))
    return ngram.loss_report(told, ["lang"])
