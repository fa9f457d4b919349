import math
import random
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from corpuslab import plans
from corpuslab.functions import pretokenize as P
from corpuslab.functions import views as V
from corpuslab.operators import bpe, contract, dedup, evaluation, hwmodel, joins, ngram, pools, sftset, translation
from corpuslab.tables import SCHEMAS, check_schema, load

TABLES = tuple(SCHEMAS)


def test_declared_schemas(spark, sf):
    assert all(check_schema(spark, sf, t) == [] for t in TABLES)


def test_published_anchors(spark):
    assert hwmodel.n_params() == 1_040_267_776
    assert round(100 * hwmodel.mfu(), 2) == 42.95 and round(100 * hwmodel.mfu(include_attention=True), 1) == 55.4
    assert [round(x, 2) for x in hwmodel.overtraining()] == [144.19, 7.21]
    plan = hwmodel.run_plan(spark).first()
    assert (plan.steps, plan.sequences_per_step, round(plan.hours_per_gpu_rate, 1)) == (71_525.6, 512.0, 76.5)
    cost = hwmodel.cost_report(spark).first()
    assert (cost.per_node_hour, cost.per_gpu_hour, cost.per_billion_tokens, cost.of_budget) == (31.65, 3.96, 16.67, 1.25)
    audit = evaluation.subsample_audit(0.416, 1172, 0.434, 500)
    assert (round(audit["se"], 4), round(audit["gap_se"], 2), round(audit["gap_se_finite"], 2)) == (0.022, 0.82, 1.08)
    verdicts = {r.format: r.verdict for r in evaluation.diagnose(evaluation.published_pairs(spark)).collect()}
    assert verdicts == {"letter": "format_artifact", "text": "comprehension_with_gap"}
    got = {r.condition: (r.passed, r.n) for r in contract.acceptance(contract.acceptance_replay(spark)).collect()}
    assert got == {"A": (5, 8), "B": (5, 5), "C": (4, 5), "D": (9, 9)}
    truth = {r.probe: r.t for r in contract.recognition_probes(spark).select("probe", contract.arith_truth(F.col("text")).alias("t")).collect()}
    assert float(truth[3]) == 91.0


def test_pieces_concatenate_and_floor_holds(spark):
    texts = ["", "It's 3 o'clock,\n\n now…", V.MARKED, "मक ा", "a" * 50, "  two  spaces ", "é💥x​y", None]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    for rule in ("letters", "letters_marks"):
        rows = df.where("text is not null").select("text", F.array_join(P.pretokenize(F.col("text"), rule), "").alias("t")).collect()
        assert all(r.text == r.t for r in rows)
    same = df.select(V.composed_view(V.decomposed_view(F.col("text"))).alias("a"), "text").where("a <> text").count()
    assert same == 0 and len(set(V.MARKED)) == len(V.MARKED) == 37


def test_bpe_training_against_brute_force(spark):
    rng = random.Random(1)
    pieces = {bytes(rng.choice(b"abc") for _ in range(rng.randint(1, 6))): rng.randint(1, 9) for _ in range(40)}
    words, want = [([*p], n) for p, n in sorted(pieces.items())], []
    for i in range(12):
        counts = Counter()
        for ids, n in words:
            for pair in zip(ids, ids[1:]):
                counts[pair] += n
        if not counts:
            break
        top = min(counts, key=lambda p: (-counts[p], p))
        want.append(top)
        words = [(bpe._join(ids, top, 256 + i), n) for ids, n in words]
    merges = bpe.train_on(pieces, 12)
    assert list(merges.pairs) == want
    hist = spark.createDataFrame([(p.decode(), n) for p, n in pieces.items()], "piece string, cnt long")
    assert bpe.train_bpe(hist, 256 + 6, "batched", pairs_per_round=1).pairs == merges.pairs[:6]
    assert merges.decode(merges.encode(b"abcabc")) == b"abcabc" and bpe.Merges(merges.pairs[:5]).fingerprint() != merges.fingerprint()
    with pytest.raises(ValueError):
        bpe.train_bpe(hist, 70_000)


def test_flat_merges_against_piecewise_ones(spark):
    rng = random.Random(4)
    pieces = {"".join(rng.choice("aabcé") for _ in range(rng.randint(1, 14))): rng.randint(1, 900) for _ in range(600)} | {"a" * n: n for n in range(1, 9)}
    want = bpe.train_on({p.encode(): n for p, n in pieces.items()}, 150)
    hist = spark.createDataFrame(list(pieces.items()), "piece string, cnt long")
    for guide in (0, 5, 300):
        assert bpe._train_batched(hist, 150 if guide == 300 else 25, 16, guide).pairs == want.pairs[: 150 if guide == 300 else 25]
    got = hist.select("piece", bpe.token_count(want)("piece").alias("n")).collect()
    assert len(got) == len(pieces) and all(r.n == len(want.encode(r.piece.encode())) for r in got)
    flat = bpe.Flat([p.encode() for p in pieces], np.array([*pieces.values()]))
    flat.merge((97, 97), 256, True)
    assert flat.counts().tolist() == [len(bpe._join([*p.encode()], (97, 97), 256)) for p in pieces]


def test_training_in_the_cluster_takes_few_looks(spark, monkeypatch):
    rng = random.Random(5)
    pieces = {"".join(rng.choice("aaabcdé") for _ in range(rng.randint(1, 12))): rng.randint(1, 400) for _ in range(1500)} | {"a" * n: 7 * n for n in range(1, 12)}
    hist = spark.createDataFrame(list(pieces.items()), "piece string, cnt long")
    looks, there = [], type(hist).mapInArrow
    monkeypatch.setattr(type(hist), "mapInArrow", lambda self, *a, **b: (looks.append(1), there(self, *a, **b))[1])
    assert bpe._train_batched(hist, 200, 16).pairs == bpe.train_on({p.encode(): n for p, n in pieces.items()}, 200).pairs
    assert len(looks) <= 8


def test_chunks_give_the_same_pieces(spark):
    rng = random.Random(6)
    texts = ["".join(rng.choice(["a", "É", "\u0e01\u0e31", "\u0301", " ", " ", "\t", "\n", "'s", "'", "12", "٣", "-", "\u00a0", "🙂"]) for _ in range(rng.randint(0, 40))) for _ in range(300)] + [None]
    df = spark.createDataFrame([(i % 2, t) for i, t in enumerate(texts)], "side int, text string")
    chunks = P.chunk_histogram(df, ["side"])
    for rule in ("letters", "letters_marks"):
        got = P.piece_histogram(chunks, rule, ["side"], "chunk", "cnt")
        assert Counter(got.collect()) == Counter(P.piece_histogram(df, rule, ["side"]).collect())
    assert chunks.agg(F.sum(F.col("cnt") * P.n_words(F.col("chunk")))).first()[0] == df.agg(F.sum(P.n_words(F.col("text")))).first()[0]


def test_packing_keeps_every_token(spark):
    docs = spark.createDataFrame([(i, list(range(1, (i * 7) % 40 + 1))) for i in range(60)], "doc_id long, ids array<int>")
    rows = bpe.pack(docs, 16, shards=3).collect()
    assert Counter(x for r in rows for x in r.ids) == Counter(x for d in docs.collect() for x in [*d.ids, 0])
    by = {}
    for r in sorted(rows, key=lambda r: (r.shard, r.seq)):
        by.setdefault(r.shard, []).append(len(r.ids))
    assert all(set(v[:-1]) <= {16} for v in by.values())
    back = docs.select("ids", bpe.from_u16(bpe.to_u16(F.col("ids"))).alias("b")).where("b <> ids").count()
    assert back == 0
    wrong = spark.createDataFrame([("aa",)], "fingerprint string")
    with pytest.raises(Exception, match="packed with"):
        bpe.require_fingerprint(wrong, "bb").collect()


@pytest.mark.parametrize("name", ["lm_unigram_totals", "lm_bigram_totals"])
def test_totals_hold_all_counts(spark, sf, name):
    test_queries_equal_their_sql(spark, sf, name)
    words = load(spark, sf, "documents").agg(F.sum(P.n_words(F.col("text")))).first()[0]
    rows = plans.load().QUERIES[name](spark, sf).collect()
    assert sum(r.tokens for r in rows) == words and all(r.once > 0 for r in rows)


def test_subsample_report_of_scored_items(spark):
    rows = [("EN", i, i % 4, 0) for i in range(200)]
    got = evaluation.subsample_report(spark.createDataFrame(rows, "lang string, item_id int, pick int, gold int"), ("lang",)).first()
    want = evaluation.subsample_audit(0.25, 200, got.acc_half, got.m)
    assert 70 < got.m < 130 and got.n == 200 and got.acc == 0.25
    assert all(math.isclose(got[k], want[k], abs_tol=1e-4) for k in want)


def test_mixture_sweep_respects_the_floor(spark, sf):
    docs = load(spark, sf, "documents").where("lang in ('en', 'es')")
    lrl = F.col("lang") == "es"
    seen = docs.withColumn("text", F.when(lrl, V.abugida_view(F.col("text"))).otherwise(F.col("text")))
    rows = bpe.mixture_sweep(seen, lrl, [0.5, 1.0], ["letters", "letters_marks"], 256 + 200, head=1500).collect()
    assert all(r.slack > -1e-9 for r in rows)
    by = {(r.rule, r.share): r for r in rows}
    assert by["letters", 1.0].floor > 2 * by["letters_marks", 1.0].floor and by["letters", 1.0].slack < by["letters", 0.5].slack


def test_tokenizers_see_all_pieces(spark):
    docs = spark.createDataFrame([("es", "aa bb aa ccc, ddd"), ("es", "ee ff aa"), ("en", "aa gg aaaa aa hh")], "lang string, text string")
    lrl = F.col("lang") == "es"
    hist = P.piece_histogram(docs, "letters")
    assert bpe.train_bpe(hist, 256 + 8, head=2).pairs == bpe.train_bpe(hist, 256 + 8).pairs
    want = P.fertility_floor(docs.where(lrl), ["lang"], "letters").first().floor
    for head in (2, 100):
        got = bpe.mixture_sweep(docs, lrl, [0.5], ["letters"], 256 + 8, head=head).first()
        merges = bpe.train_on({p.encode(): n for p, n in _mixed(docs, lrl)}, 8)
        tokens = bpe.fertility(docs.where(lrl), merges, "letters", ["lang"]).first()
        assert math.isclose(got.floor, want) and math.isclose(got.fertility, tokens.tokens / tokens.words)


def _mixed(docs, lrl):
    counts = {k: Counter({r.piece: r.cnt for r in P.piece_histogram(docs.where(c), "letters").collect()}) for k, c in ((1, lrl), (0, ~lrl))}
    return [(p, round(1e15 * sum(0.5 * counts[k][p] / sum(counts[k].values()) for k in (1, 0)))) for p in counts[1] | counts[0]]


def test_capped_weights_against_loop(spark):
    sizes = {"a": 10.0, "b": 100.0, "c": 1000.0, "d": 5.0}
    df = spark.createDataFrame(list(sizes.items()), "pool string, tokens double")
    for total, cap in ((1115.0, 1.0), (2000.0, 2.0), (600.0, 4.0)):
        got = {r.pool: r.weight for r in pools.solve_weights(df, "capped", alpha=0.0, total=total, max_epochs=cap).collect()}
        left, rest, want = 1.0, set(sizes), {}
        while rest:
            each = left / len(rest)
            over = {p for p in rest if each > cap * sizes[p] / total + 1e-12}
            if not over:
                want |= {p: each for p in rest}
                break
            for p in over:
                want[p] = cap * sizes[p] / total
                left -= want[p]
            rest -= over
        assert all(math.isclose(got[p], want[p], abs_tol=1e-9) for p in sizes), (total, cap)
    with pytest.raises(Exception, match="fill the budget"):
        pools.solve_weights(df, "capped", total=1e6, max_epochs=1.0).collect()


def test_near_duplicates_and_components(spark):
    base = " ".join(f"w{i}" for i in range(120))
    texts = [base, base + " x", base.replace("w60 ", "y "), "another text of few words", "another text of few words", ""]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.cluster for r in dedup.near_dup_clusters(df).collect()}
    assert got == {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 5}


def test_large_buckets_lose_no_link(spark):
    """Three families in one bucket (one band of one hash), ids in turn: neighbours and the least id are of other families."""
    shared = [f"s{i}" for i in range(60)]
    rows = [(i, " ".join(shared + [f"f{i % 3}w{j}" for j in range(60)] + [f"end{i}"])) for i in range(30)]
    df = spark.createDataFrame(rows, "doc_id int, text string")
    found = [sorted(map(tuple, dedup.near_dup_clusters(df, perms=1, bands=1, bucket_cap=cap).collect())) for cap in (4, 1000)]
    assert found[0] == found[1] and len({c for _, c in found[0]}) == 4  # one text is alone: its end has the least hash


def test_contamination_finds_passages_inside_words(spark):
    passages = ["one two three four five six seven eight nine ten", "alpha beta gamma", "hello there", "solo", "Case matters here now"]
    texts = ['He said "' + passages[0] + '" twice', "Q:alpha beta gamma!", "(hello there)", "xsolox", "case matters here now", passages[0], "", None, "one two three four five six seven eight nine eleven"]
    bench = spark.createDataFrame(list(enumerate(passages)), "item_id int, text string")
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")
    got = sorted(tuple(r) for r in evaluation.contaminated(bench, docs).collect())
    assert got == sorted((i, d) for i, p in enumerate(passages) for d, t in enumerate(texts) if t and p in t)


def test_ngram_overlap_against_loop(spark):
    rng = random.Random(3)
    texts = [" ".join(rng.choice("abc") for _ in range(rng.randint(0, 14))) for _ in range(30)] + [None, "  A  b\ta "]
    bench = spark.createDataFrame(list(enumerate(texts[20:])), "item_id int, text string")
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")
    of = lambda t, n: {tuple((t or "").lower().split()[i : i + n]) for i in range(len((t or "").split()) - n + 1)}
    for n in (1, 3, 5):
        want = sorted((i, d, len(of(a, n) & of(b, n))) for i, a in enumerate(texts[20:]) for d, b in enumerate(texts) if of(a, n) & of(b, n))
        assert sorted(tuple(r) for r in evaluation.ngram_overlap(bench, docs, n).collect()) == want


def test_verdicts_of_many_pairs(spark):
    rows = [(m, *r) for m in ("one", "two") for r in map(tuple, evaluation.published_pairs(spark).collect())] + [("one", "THIRD", "text", 900, 0.387), ("one", "THIRD", "letter", 900, 0.25)]
    grid = spark.createDataFrame(rows, "model string, lang string, format string, n long, acc double")
    got = {(r.model, r.lang, r.format): r.verdict for r in evaluation.diagnose_all(grid).collect()}
    pair = {"letter": "format_artifact", "text": "comprehension_with_gap"}
    assert got == {(m, "LRL", f): v for m in ("one", "two") for f, v in pair.items()} | {("one", "THIRD", "letter"): "format_artifact", ("one", "THIRD", "text"): "comprehension"}


def test_language_models_sum_to_one(spark):
    df = spark.createDataFrame([(1, "a b a c a b"), (2, "b a b")], "doc_id long, text string")
    two = ngram.train(df, 2)
    one = ngram.AddK(ngram.train(df, 1), 1.0)
    words = [r.token for r in two.select("token").distinct().collect()]
    needed = spark.createDataFrame([("a", w) for w in [*words, "unseen"]], "context string, token string")
    for model in (ngram.AddK(two, 0.5), ngram.Interpolated(two, one, 0.4), ngram.KneserNey(two, 0.5)):
        total = sum(math.exp(r.logp) for r in model.probs(needed).collect())
        assert 0.95 < total <= 1.0 + 1e-9
    with pytest.raises(Exception, match="scripts"):
        ngram.assert_same_script(spark.createDataFrame([("latin", 1.0), ("marked", 0.5)], "script string, bpb double")).collect()


def test_split_loss_against_a_loop(spark):
    rng = random.Random(5)
    rows = [(rng.choice(["en", "es", None]), i % 4 == 0, " ".join(rng.choice(["a", "B", "c", "<s>"]) for _ in range(rng.randint(0, 9)))) for i in range(60)] + [("en", True, None), ("fr", True, "zz")]
    df = spark.createDataFrame(rows, "lang string, held_out boolean, text string")
    n, m, words = Counter(), Counter(), set()
    grams = [(lang, h, ["<s>", "<s>", *t.lower().split()]) for lang, h, t in rows if t]
    for lang, h, t in grams:
        for i in range(2, len(t)):
            if not h:
                n[lang, *t[i - 2 : i + 1]] += 1
                m[lang, *t[i - 2 : i]] += 1
                words.add(t[i])
    want = Counter()
    for lang, h, t in grams:
        for i in range(2, len(t)):
            if h:
                want[lang] += math.log((n[lang, *t[i - 2 : i + 1]] + 0.1) / (m[lang, *t[i - 2 : i]] + 0.1 * (len(words) + 1)))
    for slices in (1, 3):
        got = ngram.split_loss(df, 3, 0.1, "lang", slices=slices)
        assert set(got) == set(want) and all(math.isclose(got[k], want[k], rel_tol=1e-9) for k in want)


def test_trigram_loss_where_a_text_has_marked_letters(spark, sf, tmp_path):
    docs = load(spark, sf, "documents").limit(60)
    docs.withColumn("text", F.when(F.col("doc_id") % 5 == 0, F.concat(V.abugida_view(F.col("text")), F.lit(" <s> "), "text")).otherwise(F.col("text"))).write.parquet(f"{tmp_path}/documents.parquet")
    registry, con = plans.load(), duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    want = con.sql(registry.SQL["bpb_trigram_by_lang"]).fetchall()
    got = registry.QUERIES["bpb_trigram_by_lang"](spark, str(tmp_path)).collect()
    assert got and sorted((r.lang, r.view, round(r.bits_per_byte, 5)) for r in got) == sorted((a, b, round(c, 5)) for a, b, c in want)


def test_instruction_set_invariants(spark, sf):
    conv = load(spark, sf, "conversations")
    made = sftset.synthesize_manifest(sftset.tag_turns(conv)).collect()
    for r in made:
        names = [m.name for m in r.manifest or []]
        assert len(names) == len(set(names)) and (r.manifest is None) == (r.condition == "D")
        if r.condition == "A":
            assert r.tool in names and 3 <= len(names) <= 8
        elif r.condition == "B":
            assert 2 <= len(names) <= 7 and all(m.category != r.task for m in r.manifest)
    v3 = sftset.build_set(conv, "v3")
    assert sftset.manifest_leaks(v3).count() == 0
    assert v3.where(F.exists("segments", lambda s: (s["kind"] == "manifest") & s["trainable"])).count() == 0


def test_chrf_ways_agree(spark):
    rows = [(1, "the cat sat, here.", "the cat sat here"), (2, "abc", "xyz"), (3, "same text!", "same text!"), (4, "", "ref"), (5, "a b c d", "a b d c e")]
    df = spark.createDataFrame(rows, "k long, hyp string, ref string")
    one = {r.k: r.s for r in df.select("k", translation.chrf_row("hyp", "ref").alias("s")).collect()}
    two = {r.k: r.chrf for r in translation.chrf_sentence(df, ["k"]).collect()}
    assert math.isclose(one[3], 100.0) and all(math.isclose(one[k], two.get(k, 0.0), abs_tol=1e-5) for k in one)


def test_joins_against_brute_force(spark):
    rng = random.Random(2)
    a = [(i, rng.randint(0, 2), rng.randint(0, 50)) for i in range(40)]
    b = [(100 + i, rng.randint(0, 2), rng.randint(0, 50)) for i in range(30)]
    left, right = spark.createDataFrame(a, "id long, k long, t long"), spark.createDataFrame(b, "rid long, k long, t long")
    got = {r.id: r.asof_v for r in joins.asof_join(left, right.withColumn("v", F.col("rid")), ["k"], "t", ["v"], tie="rid").collect()}
    for i, k, t in a:
        best = max(((y, r) for r, kk, y in b if kk == k and y <= t), default=(0, None))
        assert got[i] == best[1]
    bands = spark.createDataFrame([("x", 0, 10), ("y", 10, 40), ("z", 5, 12)], "band string, low long, high long")
    met = sorted((r.id, r.band) for r in joins.band_join(left, bands, F.col("t"), F.col("low"), F.col("high"), 7.0).collect())
    assert met == sorted((i, n) for i, _, t in a for n, lo, hi in (("x", 0, 10), ("y", 10, 40), ("z", 5, 12)) if lo <= t < hi)
    assert joins.salted_join(left, right.select("k", "rid"), ["k"], 5).count() == left.join(right, "k").count()


def test_plans_push_down_and_gather_first(spark, sf):
    text = load(spark, sf, "documents").where("n_chars > 100").select("doc_id")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThan(n_chars,100)]" in text and "ReadSchema: struct<doc_id:bigint,n_chars:bigint>" in text
    emb = load(spark, sf, "embeddings")
    hidden = evaluation.hidden_states(emb)
    plan = evaluation.gathered_logits(hidden, evaluation.head_rows(emb), hidden.where("needed").select("seq", "pos"))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Cross") < plan.index("LeftSemi")


def test_streams_equal_their_batch_twins(spark, sf, tmp_path):
    from corpuslab.streaming import telemetry as S

    events = load(spark, sf, "events", event_time=True)
    events.write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    by = stream.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")
    query = by.writeStream.format("memory").queryName("hours").outputMode("complete").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination()
    assert sorted(map(tuple, spark.table("hours").collect())) == sorted((r.start, r.n) for r in S.tumbling(events).collect())
    docs = load(spark, sf, "documents")
    docs.write.parquet(str(tmp_path / "docs"))
    S.pool_counters(spark.readStream.schema(docs.schema).parquet(str(tmp_path / "docs")), str(tmp_path / "pools"), str(tmp_path / "c2")).awaitTermination()
    assert spark.read.parquet(str(tmp_path / "pools")).agg(F.sum("docs")).first()[0] == docs.count()


SAMPLE = ("dom_kl_divergence", "sft_mixture_by_lang", "cloze_last_word", "hw_slow_windows_median", "ctr_responder_random", "tok_fragmentation_abugida", "tok_pack_sequences", "hw_param_table", "pool_rollup", "mix_sample", "bpb_by_lang", "sft_manifests", "ctr_responders", "mcq_accnorm_unigram", "dom_ngram_overlap", "mt_target_script_rate", "gather_logits_equal", "join_asof_event", "st_session")


@pytest.mark.parametrize("name", SAMPLE)
def test_queries_equal_their_sql(spark, sf, name):
    registry = plans.load()
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df = registry.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    want = con.sql(registry.SQL[name])
    at = [want.columns.index(c) for c in cols]

    def norm(v):
        return round(v, 6) + 0.0 if isinstance(v, float) else str(v) if hasattr(v, "isoformat") else v

    assert sorted(repr([norm(r[c]) for c in cols]) for r in df.collect()) == sorted(repr([norm(r[i]) for i in at]) for r in want.fetchall())


#: Queries that made their rows up before they read a table.
TABLED = ("ctr_acceptance_replay", "ctr_halves", "ctr_misses", "ctr_wilson", "ctr_language_divergence", "ctr_tradeoff_front", "ctr_objective_correlation", "ctr_exact_intervals", "arith_recognition", "arith_truth", "hw_cost")


@pytest.mark.parametrize("name", TABLED)
def test_queries_read_a_given_table(spark, sf, name):
    assert plans.load().QUERIES[name](spark, sf).inputFiles()
    test_queries_equal_their_sql(spark, sf, name)


def test_binomial_tails_of_any_size():
    for n in (1, 2, 8, 27, 300):
        for k in {0, 1, n // 3, n // 2, n - 1, n, n + 1}:
            for p in (0.001, 0.3, 0.5, 0.77, 0.999):
                assert abs(contract._tail(k, n, p) - sum(math.comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k, n + 1))) < 1e-10
    for n in (5_000, 4_000_000):
        assert abs(contract._tail(n // 2 + 1, n, 0.5) + contract._tail(n // 2, n, 0.5) - 1) < 1e-6
