"""Operators around the methods: joins, aggregates, windows, sets, functions, page text."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import views as V
from ..operators import joins as J
from ..sources.html import page_text
from ..tables import load
from .registry import query


def T(name):
    return lambda spark, sf_dir, **k: load(spark, sf_dir, name, **k)


docs, labels, events, bench, conv, orders, lineitem, pages = map(T, ("documents", "labels", "events", "benchmark", "conversations", "orders", "lineitem", "pages"))


@query("SELECT doc_id, lang, n_chars FROM documents JOIN labels USING (doc_id) WHERE quality = 1 AND toxic = 0")
def flt_quality_docs(spark, sf_dir):
    return docs(spark, sf_dir).select("doc_id", "lang", "n_chars").join(labels(spark, sf_dir).where("quality = 1 and toxic = 0").select("doc_id"), "doc_id")


@query("SELECT doc_id, n_chars FROM documents WHERE n_chars BETWEEN 500 AND 900")
def flt_length_band(spark, sf_dir):
    return docs(spark, sf_dir).where(F.col("n_chars").between(500, 900)).select("doc_id", "n_chars")


@query(r"SELECT doc_id FROM documents WHERE regexp_matches(text, '[{};]|\(\)|[#$%&*]{3}')")
def flt_regex_code_like(spark, sf_dir):
    return docs(spark, sf_dir).where(F.col("text").rlike(r"[{};]|\(\)|[#$%&*]{3}")).select("doc_id")


@query("SELECT lang, quality, toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY ALL")
def join_docs_labels(spark, sf_dir):
    return docs(spark, sf_dir).select("doc_id", "lang").join(labels(spark, sf_dir), "doc_id").groupBy("lang", "quality", "toxic").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_orders_lineitem(spark, sf_dir):
    both = orders(spark, sf_dir).select("o_orderkey", "o_orderpriority").join(lineitem(spark, sf_dir).hint("merge"), F.col("o_orderkey") == F.col("l_orderkey"))
    return both.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("WITH a AS (SELECT source, count(*) AS a FROM documents WHERE lang = 'en' GROUP BY 1), b AS (SELECT source, count(*) AS b FROM documents WHERE lang = 'es' GROUP BY 1) SELECT source, coalesce(a, 0) AS a, coalesce(b, 0) AS b FROM a FULL JOIN b USING (source)")
def join_full_pool_compare(spark, sf_dir):
    d = docs(spark, sf_dir)
    one = lambda lang, c: d.where(F.col("lang") == lang).groupBy("source").agg(F.count(F.lit(1)).alias(c))
    return one("en", "a").join(one("es", "b"), "source", "full").select("source", F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b"))


@query("SELECT lang, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels) GROUP BY lang")
def join_semi_labelled(spark, sf_dir):
    return docs(spark, sf_dir).select("doc_id", "lang").join(labels(spark, sf_dir).select("doc_id"), "doc_id", "left_semi").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT lang, count(*) AS n FROM documents d WHERE NOT EXISTS (SELECT 1 FROM benchmark b WHERE contains(d.text, b.text)) GROUP BY lang")
def join_anti_decontaminated(spark, sf_dir):
    from ..operators.evaluation import contaminated

    d = docs(spark, sf_dir)
    return d.select("doc_id", "lang").join(contaminated(bench(spark, sf_dir), d).select("doc_id").distinct(), "doc_id", "left_anti").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT r_name, s AS shots FROM region CROSS JOIN (VALUES (0), (10), (25)) t(s)")
def join_cross_grid(spark, sf_dir):
    return T("region")(spark, sf_dir).select("r_name").crossJoin(F.broadcast(spark.createDataFrame([(0,), (10,), (25,)], "shots int")))


_BANDS = "(VALUES ('short', 0, 500), ('middle', 500, 3000), ('long', 3000, 1000000)) b(band, low, high)"


@query(f"SELECT band, count(*) AS n FROM documents JOIN {_BANDS} ON n_chars >= low AND n_chars < high GROUP BY band")
def join_range_length_band(spark, sf_dir):
    bands = spark.createDataFrame([("short", 0, 500), ("middle", 500, 3000), ("long", 3000, 1_000_000)], "band string, low long, high long")
    return J.band_join(docs(spark, sf_dir).select("doc_id", "n_chars"), bands, F.col("n_chars"), F.col("low"), F.col("high"), 1000.0).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT a.event_id, b.event_id AS other FROM events a JOIN events b ON a.user_id = b.user_id AND epoch(b.ts) > epoch(a.ts) AND epoch(b.ts) <= epoch(a.ts) + 7200 WHERE a.event_type = 'error'")
def join_interval_error_after(spark, sf_dir):
    e = events(spark, sf_dir).select("event_id", "ts", "user_id", "event_type")
    after = e.select(F.col("event_id").alias("other"), F.col("ts").alias("ts2"), "user_id")
    return J.interval_join(e.where("event_type = 'error'"), after, ["user_id"], "ts", "ts2", 7200).select("event_id", "other")


@query("""WITH a AS (SELECT * FROM events WHERE event_type = 'error'), b AS (SELECT user_id, ts, event_id, value FROM events WHERE event_type = 'purchase')
SELECT a.event_id, (SELECT b.event_id FROM b WHERE b.user_id = a.user_id AND b.ts <= a.ts ORDER BY b.ts DESC, b.event_id DESC LIMIT 1) AS asof_event FROM a""")
def join_asof_event(spark, sf_dir):
    e = events(spark, sf_dir).select("event_id", "ts", "user_id", "event_type")
    right = e.where("event_type = 'purchase'").select("user_id", "ts", "event_id", F.col("event_id").alias("event"))
    return J.asof_join(e.where("event_type = 'error'").select("event_id", "ts", "user_id"), right, ["user_id"], "ts", ["event"], tie="event_id").select("event_id", "asof_event")


@query("SELECT l_partkey, count(*) AS n, round(sum(l_quantity), 2) AS quantity, max(p_brand) AS brand FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def join_skew_safe(spark, sf_dir):
    part = T("part")(spark, sf_dir).select(F.col("p_partkey").alias("l_partkey"), "p_brand")
    return J.salted_join(lineitem(spark, sf_dir).select("l_orderkey", "l_linenumber", "l_partkey", "l_quantity"), part, ["l_partkey"], 4).groupBy("l_partkey").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.max("p_brand").alias("brand"))


@query("SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM customer JOIN orders ON c_custkey = o_custkey) WHERE r <= 2")
def join_lateral_topk(spark, sf_dir):
    o = orders(spark, sf_dir).select("o_orderkey", "o_custkey", "o_totalprice")
    both = T("customer")(spark, sf_dir).select("c_custkey").join(o, F.col("c_custkey") == F.col("o_custkey"))
    return both.withColumn("r", F.row_number().over(Window.partitionBy("c_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r <= 2").select("c_custkey", "o_orderkey")


@query("SELECT item_id, length(a.text) AS en_chars, strlen(" + V.sql_abugida("a.text") + ") AS lrl_bytes FROM benchmark a")
def pair_items(spark, sf_dir):
    b = bench(spark, sf_dir)
    other = b.select("item_id", V.abugida_view(F.col("text")).alias("t2"))
    return b.join(other, "item_id").select("item_id", F.length("text").cast("long").alias("en_chars"), F.octet_length("t2").cast("long").alias("lrl_bytes"))


@query("SELECT role, turn % 3 AS part, count(*) AS n, grouping_id(role, turn % 3)::int AS level FROM conversations GROUP BY CUBE (role, turn % 3)")
def agg_cube_role_cond(spark, sf_dir):
    return conv(spark, sf_dir).withColumn("part", F.col("turn") % 3).cube("role", "part").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("int").alias("level"))


@query("SELECT n_regionkey, c_mktsegment, count(*) AS n, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY GROUPING SETS ((n_regionkey, c_mktsegment), (n_regionkey), ())")
def agg_grouping_sets_nation(spark, sf_dir):
    both = T("customer")(spark, sf_dir).join(F.broadcast(T("nation")(spark, sf_dir)), F.col("c_nationkey") == F.col("n_nationkey"))
    return both.groupingSets([["n_regionkey", "c_mktsegment"], ["n_regionkey"], []], "n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@query(r"SELECT lang, count(DISTINCT w) AS words FROM (SELECT lang, unnest(regexp_extract_all(lower(text), '\S+')) AS w FROM documents) GROUP BY lang")
def agg_distinct_words(spark, sf_dir):
    w = docs(spark, sf_dir).select("lang", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\S+"), F.lit(0))).alias("w"))
    return w.groupBy("lang").agg(F.countDistinct("w").alias("words"))


@query("SELECT event_type, count(*) FILTER (value > 50) AS high, count(*) AS n, max_by(event_id, [value, event_id]) AS top FROM events GROUP BY 1")
def agg_filtered(spark, sf_dir):
    return events(spark, sf_dir).groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.count(F.lit(1)).alias("n"), F.max_by("event_id", F.struct("value", "event_id")).alias("top"))


@query("SELECT lang, quantile_cont(n_chars, 0.5) AS median, round(quantile_cont(n_chars, 0.9), 4) AS p90, mode(source) IS NOT NULL AS has_mode FROM documents GROUP BY lang")
def agg_percentiles(spark, sf_dir):
    return docs(spark, sf_dir).groupBy("lang").agg(F.percentile("n_chars", F.lit(0.5)).alias("median"), F.round(F.percentile("n_chars", F.lit(0.9)), 4).alias("p90"), F.mode("source").isNotNull().alias("has_mode"))


@query("SELECT lang, count(*) FILTER (toxic = 0) AS t0, count(*) FILTER (toxic = 1) AS t1 FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def agg_pivot_lang_label(spark, sf_dir):
    both = docs(spark, sf_dir).select("doc_id", "lang").join(labels(spark, sf_dir), "doc_id")
    return both.groupBy("lang").pivot("toxic", [0, 1]).agg(F.count(F.lit(1))).select("lang", F.coalesce("0", F.lit(0)).alias("t0"), F.coalesce("1", F.lit(0)).alias("t1"))


@query("SELECT round(corr(l_quantity, l_extendedprice), 6) AS r, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem")
def agg_correlation(spark, sf_dir):
    return lineitem(spark, sf_dir).agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"))


@query()
def agg_sketches(spark, sf_dir):
    """Distinct words by a sketch of bounded size, for vocabularies too large to count."""
    w = docs(spark, sf_dir).select("lang", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\S+"), F.lit(0))).alias("w"))
    return w.groupBy("lang").agg(F.hll_sketch_estimate(F.hll_sketch_agg("w")).alias("estimate"), F.approx_count_distinct("w").alias("approx"))


@query("SELECT lang, source, n, rank() OVER (PARTITION BY lang ORDER BY n DESC)::int AS rk, dense_rank() OVER (PARTITION BY lang ORDER BY n DESC)::int AS dr, round(percent_rank() OVER (PARTITION BY lang ORDER BY n DESC), 6) AS pr, round(cume_dist() OVER (PARTITION BY lang ORDER BY n DESC), 6) AS cd FROM (SELECT lang, source, count(*) AS n FROM documents GROUP BY ALL)")
def win_rank_sources(spark, sf_dir):
    w = Window.partitionBy("lang").orderBy(F.desc("n"))
    by = docs(spark, sf_dir).groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n"))
    return by.select("*", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("SELECT doc_id, sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING)::bigint AS running, ntile(4) OVER (PARTITION BY source ORDER BY doc_id)::int AS quarter FROM documents")
def win_running_tokens(spark, sf_dir):
    w = Window.partitionBy("source").orderBy("doc_id")
    return docs(spark, sf_dir).select("doc_id", F.sum("n_chars").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.ntile(4).over(w).alias("quarter"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 1 PRECEDING), 6) AS m, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS f FROM events")
def win_trailing_mean_events(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(spark, sf_dir).select("event_id", F.round(F.avg("value").over(w.rowsBetween(-3, -1)), 6).alias("m"), F.first("event_id").over(w).alias("f"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::bigint RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day_before FROM events")
def win_range_frame_events(spark, sf_dir):
    s = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000).cast("long")
    return events(spark, sf_dir).withColumn("s", s).select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-86_400, 0)).alias("day_before"))


@query("SELECT lang, source, round(n::double / sum(n) OVER (PARTITION BY lang), 6) AS share FROM (SELECT lang, source, sum(n_chars)::bigint AS n FROM documents GROUP BY ALL)")
def win_share_of_pool(spark, sf_dir):
    by = docs(spark, sf_dir).groupBy("lang", "source").agg(F.sum("n_chars").alias("n"))
    return by.select("lang", "source", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("lang")), 6).alias("share"))


@query("SELECT conv_id, turn, role, lag(role) OVER w AS before, lead(turn) OVER w - turn AS gap FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def win_turn_gaps(spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return conv(spark, sf_dir).select("conv_id", "turn", "role", F.lag("role").over(w).alias("before"), (F.lead("turn").over(w) - F.col("turn")).alias("gap"))


@query(r"SELECT w, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '\S+')) AS w FROM documents) GROUP BY w ORDER BY n DESC, w LIMIT 25")
def topk_global_words(spark, sf_dir):
    w = docs(spark, sf_dir).select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\S+"), F.lit(0))).alias("w"))
    return w.groupBy("w").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "w").limit(25)


@query(f"SELECT doc_id FROM documents WHERE {V.sql_bucket('sample', 'doc_id')} % 10 = 0")
def sample_md5(spark, sf_dir):
    """A sampling operator: a share that follows from md5 of the key."""
    return docs(spark, sf_dir).where(V.bucket("sample", F.col("doc_id")) % 10 == 0).select("doc_id")


def _vocab(lang: str) -> str:
    return rf"SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[\p{{L}}]+')) AS w FROM documents WHERE lang = '{lang}'"


def _words(spark, sf_dir, lang):
    return docs(spark, sf_dir).where(F.col("lang") == lang).select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"[\p{L}]+"), F.lit(0))).alias("w"))


@query(f"SELECT w FROM ({_vocab('en')}) INTERSECT SELECT w FROM ({_vocab('es')})")
def set_vocab_intersection(spark, sf_dir):
    return _words(spark, sf_dir, "en").intersect(_words(spark, sf_dir, "es"))


@query(f"SELECT count(*) AS n FROM (SELECT w FROM ({_vocab('es')}) EXCEPT SELECT w FROM ({_vocab('en')}))")
def set_vocab_except(spark, sf_dir):
    return _words(spark, sf_dir, "es").exceptAll(_words(spark, sf_dir, "es").limit(0)).subtract(_words(spark, sf_dir, "en")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT source AS name FROM documents UNION SELECT event_type FROM events")
def set_union_sources(spark, sf_dir):
    return docs(spark, sf_dir).select(F.col("source").alias("name")).unionByName(events(spark, sf_dir).select(F.col("event_type").alias("name"))).distinct()


@query("SELECT doc_id, md5(text) AS d, length(text) AS n, instr(text, 'the') AS at, lower(substr(text, 1, 5)) AS head, lpad(doc_id::varchar, 6, '0') AS id, starts_with(text, 'The') AS s FROM documents")
def fn_string_profile(spark, sf_dir):
    t = F.col("text")
    return docs(spark, sf_dir).select("doc_id", F.md5(t).alias("d"), F.length(t).cast("long").alias("n"), F.instr(t, "the").cast("long").alias("at"), F.lower(F.substring(t, 1, 5)).alias("head"), F.lpad(F.col("doc_id").cast("string"), 6, "0").alias("id"), t.startswith("The").alias("s"))


@query("SELECT date_trunc('day', ts) AS day, count(*) AS n, floor(min(epoch(ts)))::bigint AS first FROM events GROUP BY 1")
def fn_date_events(spark, sf_dir):
    return events(spark, sf_dir).groupBy(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day")).agg(F.count(F.lit(1)).alias("n"), F.floor(F.min(F.unix_micros(F.col("ts").cast("timestamp"))) / 1_000_000).alias("first"))


@query("SELECT event_id, round(ln(1 + abs(value)), 6) AS l, round(sqrt(abs(value)), 6) AS s, floor(value)::bigint AS f, event_id % 7 AS m, greatest(value, 50) AS g FROM events WHERE value IS NOT NULL")
def fn_math_z(spark, sf_dir):
    v = F.col("value")
    return events(spark, sf_dir).where("value is not null").select("event_id", F.round(F.log(1 + F.abs(v)), 6).alias("l"), F.round(F.sqrt(F.abs(v)), 6).alias("s"), F.floor(v).alias("f"), (F.col("event_id") % 7).alias("m"), F.greatest(v, F.lit(50.0)).alias("g"))


@query(rf"SELECT item_id, greatest(len(t) - 2, 0)::bigint AS n, array_to_string(t[1:3], ' ') AS first FROM (SELECT item_id, regexp_extract_all(lower(text), '\S+') AS t FROM benchmark)")
def fn_array_ngrams(spark, sf_dir):
    from ..functions.arrays import grams
    from ..operators.ngram import tokens

    g = grams(tokens(F.col("text")), 3)
    return bench(spark, sf_dir).select("item_id", F.size(g).cast("long").alias("n"), F.get(g, F.lit(0)).alias("first"))


@query("SELECT event_id, (props::json ->> 'k')::bigint AS k FROM events WHERE props IS NOT NULL")
def fn_json_props(spark, sf_dir):
    return events(spark, sf_dir).where("props is not null").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query(r"SELECT page_id, regexp_extract(url, '^(https?)://', 1) AS scheme, regexp_extract(url, '://([^/?#]+)', 1) AS host, regexp_extract(url, '\?([^#]*)', 1) AS query FROM pages")
def fn_url_parts(spark, sf_dir):
    u = F.col("url")
    return pages(spark, sf_dir).select("page_id", F.parse_url(u, F.lit("PROTOCOL")).alias("scheme"), F.parse_url(u, F.lit("HOST")).alias("host"), F.coalesce(F.parse_url(u, F.lit("QUERY")), F.lit("")).alias("query"))


@query(r"""WITH a AS (SELECT page_id, regexp_replace(regexp_replace(html, '(?s)<!--.*?-->|<script.*?</script>|<style.*?</style>|<nav.*?</nav>|<head.*?</head>|<footer.*?</footer>|<div class="ad">.*?</div>', ' ', 'g'), '<[^>]*>', ' ', 'g') AS t FROM pages)
SELECT page_id, trim(regexp_replace(replace(replace(replace(replace(replace(t, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&middot;', chr(183)), '&amp;', '&'), '\s+', ' ', 'g')) AS text FROM a""")
def src_page_text(spark, sf_dir):
    return pages(spark, sf_dir).select("page_id", page_text(F.col("html")).alias("text"))


@query("SELECT o_orderstatus, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1 HAVING count(*) > 100")
def agg_two_level(spark, sf_dir):
    o = orders(spark, sf_dir).select("o_orderkey", "o_orderstatus", "o_totalprice")
    sums = J.two_level_sum(o, ["o_orderstatus"], F.col("o_totalprice"), "total").join(J.two_level_sum(o, ["o_orderstatus"], F.lit(1), "n"), "o_orderstatus")
    return sums.where("n > 100").select("o_orderstatus", "n", F.round("total", 2).alias("total"))
