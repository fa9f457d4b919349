import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash

public_tokenizers = pytest.importorskip("public_tokenizers")

from corpuslab.llm import bpe, components, htmltext, lmscore, mixing, ogg, quality, rangecoder, sharding, simhash, tokenfiles, urlfilter  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, shard int, size long, fp string, kept int"
WORDS = "the of and to in that is for on with as by at from this it an are was be".split()


def odd_documents(spark):
    """Nulls in any column, empty, blank, repeated and long texts, ties, and columns with clashing names."""
    rng = random.Random(5)
    long = " ".join(rng.choice(WORDS) + str(rng.randint(0, 999)) for _ in range(6000))
    near = " ".join(f"word{i}" for i in range(300))
    texts = [None, "", "  \n ", "one two", "one two", long, near, near + " more", near.replace("word7 ", "other "), "Zoë's café\n\ncosts 5€ <|endoftext|> now", "a\tb\x0bc\x1cd", "x " * 200]
    rows = [(i, t, "en", ("s1", None, "s2")[i % 3], None, 1, 2, "z", 0) for i, t in enumerate(texts)]
    rows += [rows[3], (None, "one two", None, None, None, None, None, None, None), (None, None, None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


def words_of(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def test_words_of_slices():
    from corpuslab.llm.common import Words, slices

    rng = random.Random(9)
    texts = [None if i % 50 == 3 else " ".join(rng.choice(["Ab", "c", "Éd", "x\n\ty"]) for _ in range(rng.randint(0, 30))) for i in range(500)]
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], ["text"])
    for low in (False, True):
        got = []
        for part in slices(iter([batch]), 0, 700):
            w = Words(part.column(0), lower=low)
            got += [[w.distinct[c] for c in w.codes[a:b]] for a, b in zip(w.starts, w.starts[1:])]
        want = [(t or "").encode().split() for t in texts]
        assert got == ([[x.lower() for x in t] for t in want] if low else want)


def test_ogg_round_trip_and_damage(spark):
    for n in (0, 1, 192, 959, 5000, 70_000):
        payload = ogg.pad(bytes(random.Random(n).randbytes(n)))
        media = ogg.mux(payload)
        streams = ogg.demux(media)
        assert len(payload) % 192 == 0 and ogg.rebuild(streams) == payload and len(streams) == 2
        times = [t for x in streams.values() for t, _ in x["packets"]]
        assert sorted(times) == list(range(0, len(payload), ogg.FRAME))
        broken = bytearray(media)
        broken[len(media) // 2] ^= 1
        with pytest.raises(ogg.OggError):
            ogg.rebuild(ogg.demux(bytes(broken)))
    def slow(b):
        c = 0
        for x in b:
            c ^= x << 24
            for _ in range(8):
                c = (c << 1 ^ 0x04C11DB7 if c & 0x80000000 else c << 1) & 0xFFFFFFFF
        return c
    assert ogg.page_crc(b"OggS and more") == slow(b"OggS and more")
    docs = odd_documents(spark)
    rows = ogg.digest(docs).collect()
    assert len(rows) == docs.count() and all(r.error is None and r.payload_bytes % 192 == 0 and r.payload_bytes > 0 for r in rows)
    lost = spark.createDataFrame([(1, None), (2, bytearray(b"nothing"))], "doc_id long, media binary")
    assert [r.payload for r in ogg.read(lost).collect()] == [None, None]


def test_feistel_is_a_bijection_and_shards_are_even(spark):
    for n in (1, 2, 3, 17, 1000, 4097):
        out = sharding.permute(np.arange(n), n)
        assert sorted(out) == list(range(n)) and list(sharding.permute(out, n, inverse=True)) == list(range(n))
    docs = odd_documents(spark)
    rows = sharding.shard_documents(docs, 4).collect()
    sizes = Counter(r.shard for r in rows)
    assert len(rows) == docs.count() and max(sizes.values()) - min(sizes.values()) <= 1
    for s in sizes:
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(sizes[s]))
    again = sharding.shard_documents(docs.repartition(7), 4).collect()
    assert sorted(map(str, rows)) == sorted(map(str, again))
    assert sharding.shard_documents(docs.limit(0)).count() == 0
    assert 0 <= sharding.locate(1, 2, 15, 4) < 15


def brute_fingerprint(text):
    w = lower(text).encode().split()
    grams = [b" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or ([b" ".join(w)] if w else [])
    h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if h and 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash_against_brute_force(spark):
    docs = odd_documents(spark)
    rows = docs.select("doc_id", "text").collect()
    got = simhash.near_duplicates(docs).collect()
    assert len(got) == len(rows)
    fps = [(r.doc_id, brute_fingerprint(r.text)) for r in rows]
    assert sorted((str(r.doc_id), r.fingerprint) for r in got) == sorted((str(i), f"{f:016x}") for i, f in fps)
    nodes = sorted({f for _, f in fps})
    root = {f: f for f in nodes}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in nodes:
        for b in nodes:
            if (a ^ b).bit_count() <= 4:
                root[find(a)] = find(b)
    least = {}
    for i, f in fps:
        if i is not None:
            least[find(f)] = min(i, least.get(find(f), i))
    want = {f"{f:016x}": least.get(find(f)) for f in nodes}
    assert all(want[r.fingerprint] == r.component_id for r in got)
    kept = simhash.keep_one(docs)
    assert kept.count() == len({find(f) for f in nodes}) and kept.columns == docs.columns
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


def test_anchors_cover_and_split_agrees(spark):
    rng = random.Random(1)
    points = []
    for _ in range(150):
        x = rng.getrandbits(64)
        y = x
        for b in rng.sample(range(64), rng.randint(1, 6)):
            y ^= 1 << b
        points += [x, y]
    signed = [p - (1 << 64) if p >> 63 else p for p in set(points)]
    df = spark.createDataFrame([(p,) for p in signed], "fp long")
    want = sorted((a, b) for a in signed for b in signed if a < b and ((a ^ b) & (1 << 64) - 1).bit_count() <= 4)
    for split in (False, True):
        assert sorted(map(tuple, simhash.links(df, split=split).collect())) == want


def test_components(spark):
    chain = [(i, i + 1) for i in range(40)] + [(100, 200), (150, 200)]
    got = {r.node: r.root for r in components.components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[200] == got[150] == got[100] == 100
    assert components.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_components_of_random_links(spark):
    rng = random.Random(12)
    for n, m in ((40, 30), (200, 230), (60, 20)):
        pairs = [(rng.randrange(n), rng.randrange(n)) for _ in range(m)] + [(n, n + i) for i in range(1, 80)]
        root = list(range(n + 80))

        def find(x):
            while root[x] != x:
                x = root[x]
            return x

        for a, b in pairs:
            a, b = sorted((find(a), find(b)))
            root[b] = a
        got = {r.node: r.root for r in components.components(spark.createDataFrame(pairs, "a long, b long")).collect()}
        assert got == {x: find(x) for p in pairs for x in p}


def test_near_copies_round_one_point(spark):
    rng = random.Random(2)
    words = [f"w{rng.randint(0, 10**6)}" for _ in range(400)]
    texts = [" ".join(w for k, w in enumerate(words) if k != i) for i in range(120)] + ["other words entirely " + str(i) for i in range(30)]
    docs = spark.createDataFrame([(i, t, 5, "k") for i, t in enumerate(texts)], "doc_id long, text string, fp long, root string")
    fps = {i: brute_fingerprint(t) for i, t in enumerate(texts)}
    distinct = set(fps.values())
    links = {f: sum(1 for g in distinct if g != f and (f ^ g).bit_count() <= 4) for f in distinct}
    for most in (simhash.LOAD, 0):  # whole anchors, or split ones
        rows, classes = simhash.duplicate_classes(docs, most=most)
        got = {r.doc_id: (r.links, r.component_id) for r in rows.join(classes, "fp").collect()}
        assert all(got[i][0] == links[f] for i, f in fps.items())
        assert len({got[i][1] for i in range(120)}) <= len({fps[i] for i in range(120)})


def test_lm_base_is_exact_and_model_is_a_probability(spark):
    docs = odd_documents(spark)
    rows = docs.select("doc_id", "text").collect()
    counts = Counter()
    for r in rows:
        if zlib.crc32(str("" if r.doc_id is None else r.doc_id).encode()) % 7 != 2:
            counts.update([*words_of(lower(r.text)), None])
    n, v = sum(counts.values()), len(counts)
    want = sorted((str(r.doc_id), round(sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in [*words_of(lower(r.text)), None]), 6), len(words_of(r.text)) + 1) for r in rows)
    for head in (lmscore.HEAD, 5):  # all words broadcast, or most of them by the join
        got = lmscore.score(docs, head=head).collect()
        assert sorted((str(r.doc_id), round(r.base_score, 6), r.n_tokens) for r in got) == want
        assert all(r.train_tokens == n and r.score < 0 for r in got)
    assert lmscore.score(docs.limit(0)).count() == 0


def test_log_frequency_filter(spark):
    rng = np.random.default_rng(2)
    keys, c = rng.integers(-(2**62), 2**62, 3000) & ~1, rng.zipf(1.5, 3000).clip(1, 10**6)
    f = lmscore.build_filter(spark.createDataFrame([(int(a), int(b)) for a, b in zip(keys, c)], "key long, c long"))
    q = f.counts(keys.view(np.uint64))
    assert (q >= lmscore.quantise(c)).all() and (q != lmscore.quantise(c)).mean() < 0.05
    assert (f.counts(rng.integers(1, 2**62, 20_000).astype(np.uint64) | np.uint64(1)) > 0).mean() < 0.03
    near = lmscore.restore(lmscore.quantise(c)) / c
    assert (near > 0.6).all() and (near < 1.6).all()


def test_filter_too_large_to_broadcast_answers_alike(spark):
    docs = odd_documents(spark)
    want = sorted((str(r.doc_id), r.n_tokens, r.score) for r in lmscore.score(docs).collect())
    keys = spark.range(0, 1_000_000).selectExpr("xxhash64(id) div 2 * 2 AS key", "1L AS c")
    f = lmscore.build_filter(keys, max_bits=lmscore.SEGMENT)
    assert f.hashes == 7 and f.segments * lmscore.SEGMENT > 10_000_000
    got = sorted((str(r.doc_id), r.n_tokens, r.score) for r in lmscore.score(docs, max_bits=0).collect())  # all segments stay a table
    assert lmscore.score(docs.limit(0), max_bits=0).count() == 0
    assert len(got) == len(want) and all(a[:2] == b[:2] and math.isclose(a[2], b[2], rel_tol=1e-9) for a, b in zip(got, want))


def test_pairs_seen_once_count(spark):
    docs = spark.createDataFrame([(2, "the cat sat on a mat", False), (3, "a dog ran to the gate", False)], "doc_id long, text string, held_out boolean")
    model, _ = lmscore.train(docs)
    seen = lmscore.Tokens.of(pa.array(["the cat sat on a mat"])).pairs()
    assert (model.filter.counts(seen) == 1).all()


def test_model_sums_to_one(spark, sf):
    from corpuslab.llm.common import table

    docs = table(spark, "/root/testdata/sf0.01", "documents").selectExpr("doc_id", "text", "doc_id % 7 = 2 AS held_out")
    model, words = lmscore.train(docs)
    vocabulary = [r.key for r in words.select("key").collect()]
    key = np.array(vocabulary).view(np.uint64)
    word = lmscore.restore(model.filter.counts(key))
    assert math.isclose(((word + 1).sum() + 1) / model.mass, 1, abs_tol=0.02)  # the filter's false positives
    for before in key[np.argsort(-word)[:12]]:
        both = lmscore.restore(model.filter.counts(lmscore.mix(np.full(len(key), before), key) | np.uint64(1)))
        c = lmscore.restore(model.filter.counts(np.array([before])))[0]
        assert 0.8 < np.minimum(both, np.minimum(word, c)).sum() / c < 1.25


def test_equal_texts_score_alike(spark, sf):
    from corpuslab.llm.common import table

    docs = table(spark, sf, "documents")
    again = docs.selectExpr("doc_id + 100000 AS doc_id", "text").union(docs.select("doc_id", "text")).repartition(5)
    for head in (lmscore.HEAD, 500):
        by = {}
        told = {r.doc_id: (r.base_score, r.score, r.n_known) for r in lmscore.score(again, head=head).collect()}
        for r in again.collect():
            by.setdefault(r.text, set()).add(told[r.doc_id])
        assert all(len(v) == 1 for v in by.values())


def test_weights_rest_on_all_training_documents(spark):
    docs = spark.range(0, 2600).selectExpr("id AS doc_id", "concat('one two ', id % 7) AS text")
    docs = docs.withColumn("held_out", lmscore.is_held_out(docs.doc_id))
    model, _ = lmscore.train(docs)
    shared = spark.sparkContext.broadcast(model)
    seen = lmscore.ratios(lmscore.read(docs, model, shared), model, shared)
    assert seen.sum() == model.tokens == 4 * docs.where("not held_out").count() > 8000


def brute_base(text):
    w = words_of(text)
    windows = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    hit = {i + k for i in range(len(w) - 2) if windows[tuple(w[i : i + 3])] > 1 for k in range(3)}
    lines = [x for x in (text or "").split("\n") if words_of(x)]
    return len(w), sum(map(len, w)), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(hit)


def test_quality_base_rules_and_verdicts(spark, sf):
    extra = [(50, "a b c a b c\nx y\nx y\n \n z", "en", None, None, None, None, None, None), (51, "é€ # $ 日本 <b>", "fr", None, None, None, None, None, None)]
    docs = odd_documents(spark).union(spark.createDataFrame(extra, SCHEMA))
    got = quality.judge(docs, quality.Model(np.zeros(2 * quality.BUCKETS, np.float32), {}, 0.0)).collect()
    for r in got:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == brute_base(r.text), r.doc_id
        assert r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words)
    from corpuslab.llm.common import table

    docs, labels = table(spark, "/root/testdata/sf0.01", "documents"), table(spark, "/root/testdata/sf0.01", "labels")
    judged = quality.judge(docs, quality.fit(docs, labels)).join(labels, "doc_id").where("not base_failed")
    by = {(r.quality, r.toxic): r.k for r in judged.groupBy("quality", "toxic").agg({"kept": "count", "llr": "avg"}).withColumnRenamed("avg(llr)", "k").collect()}
    assert by[1, 0] > by[1, 1] and by[1, 0] > by[0, 0]
    kept = judged.where("quality = 1 and toxic = 0").selectExpr("avg(int(kept)) k").first().k
    assert kept > 0.8
    assert quality.fit(docs.limit(0), labels.limit(0)).threshold == 0.0


def test_all_labelled_documents_are_used(spark, sf):
    from pyspark.sql import functions as F

    labels = spark.range(40_000).select(F.col("id").alias("doc_id"), F.lit(1).alias("quality"), (F.col("id") % 5 == 0).cast("int").alias("toxic"))
    roles = quality.split_labels(labels)
    got = {r.role: r.n for r in roles.groupBy("role").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert got[quality.FIT] > 20_000 and got[quality.CLEAN] + got[quality.UNCLEAN] > 6_000
    assert got[quality.FIT] + got[quality.CLEAN] == 32_000
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    one, two = quality.fit(docs, labels), quality.fit(docs, labels, local=0)
    assert (one.weights == two.weights).all() and one.offsets == two.offsets and one.threshold == two.threshold
    assert quality._median(np.array([1, 4, 6]), np.array([2, 1, 1])) == 2.5 and quality._median(np.array([1, 4]), np.array([1, 2])) == 4


def test_fit_keeps_one_python_worker_a_task(spark, sf, monkeypatch):
    """No Python pass of the fit feeds another one of the same stage, each of which keeps a worker of its own."""
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    fed, whole = [], type(docs).mapInArrow

    def seen(df, *args):
        fed.append("MapInArrow" in df._jdf.queryExecution().optimizedPlan().toString())
        return whole(df, *args)

    monkeypatch.setattr(type(docs), "mapInArrow", seen)
    assert quality.fit(docs, labels).threshold != 0.0 and fed == [False, False]


def test_subset_sum_and_water_fill(spark):
    rng = random.Random(3)
    for _ in range(200):
        lengths = np.array(sorted(rng.sample(range(0, 20), rng.randint(1, 5))))
        counts = np.array([rng.randint(1, 3) for _ in lengths])
        budget = rng.randint(0, int((lengths * counts).sum()) + 2)
        taken = mixing.fit_counts(lengths, counts, budget)
        assert (taken >= 0).all() and (taken <= counts).all() and (lengths * taken).sum() <= max(budget, 0) or budget >= (lengths * counts).sum()
    lengths = np.arange(1, 3000)
    counts = np.full(2999, 3)
    budget = int((lengths * counts).sum() * 0.37)
    assert (lengths * mixing.fit_counts(lengths, counts, budget)).sum() == budget
    t = mixing.water_fill([10, 100, 1000], [1, 2, 3])
    assert math.isclose(sum(t), 1110) and t[0] == 30 and all(x <= 3 * s + 1e-9 for x, s in zip(t, [10, 100, 1000]))
    docs = odd_documents(spark)
    rows = mixing.mix_sizes(docs).collect()
    assert len(rows) == docs.count()
    again = mixing.mix_sizes(docs.repartition(5)).collect()
    assert sorted(map(str, rows)) == sorted(map(str, again))
    by = {}
    for r in rows:
        assert r.taken <= 3 * r.size
        by.setdefault(r.source_size, [r.target, 0])[1] += r.taken
    assert mixing.mix_sizes(docs.limit(0)).count() == 0


def test_range_coder_round_trip_and_damage():
    rng = np.random.default_rng(4)
    for n in (0, 1, 2, 95, 96, 97, 3000):
        for alphabet in (2, 300, 49_408):
            ids = np.minimum(rng.geometric(0.05, n), alphabet - 1)
            keys, lengths, out = rangecoder.unpack_block(rangecoder.pack_block([7, None], [n, 0], ids, alphabet))
            assert keys == [7, None] and lengths == [n, 0] and (out == ids).all()
    again = np.tile(np.arange(100), 200)
    block = rangecoder.pack_block([1], [len(again)], again, 49_408)
    assert len(block) < len(again)
    for at in (30, len(block) - 1):
        broken = bytearray(block)
        broken[at] ^= 1
        with pytest.raises(rangecoder.BlockError):
            rangecoder.unpack_block(bytes(broken))


def test_token_files_against_the_library(spark):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    known = Tokenizer.from_file(path)
    docs = odd_documents(spark)
    got = tokenfiles.digest(docs, path).collect()
    rows = sorted(docs.select("doc_id", "text").collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0))
    want, at, places = [], 0, {}
    for r in rows:
        ids = known.encode(r.text or "", add_special_tokens=False).ids + [2]
        want.append((str(r.doc_id), len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        places.setdefault(r.doc_id, []).append(at)
        at += len(ids)
    assert sorted((str(r.doc_id), r.n_tokens, r.ids_crc32) for r in got) == sorted(want)
    assert {r.doc_id: r.start for r in got if len(places[r.doc_id]) == 1} == {k: v[0] for k, v in places.items() if len(v) == 1}
    assert tokenfiles.digest(docs.limit(0), path).count() == 0


def test_words_are_cut_as_the_library_cuts():
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    known, mine = Tokenizer.from_file(path), tokenfiles.WordCoder(path)
    assert mine.inner is not None
    rng = random.Random(3)
    letters = list("aZ'sStTdDlLmMveRE0 5.,!-_$é É ÀßñÑœŒ€“”…—·×÷ªºµĳİıŉſ日́​\xa0\x85\x1c") + ["<|endoftext|>", "<|", "'ll", "Don't", "ŸÿÄ", "½", "²"]
    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 25))) for _ in range(4000)] + ["", None, "x" * 5000]
    for memory in (tokenfiles.MEMORY, 500):
        kept, tokenfiles.MEMORY = tokenfiles.MEMORY, memory
        try:
            got = [mine.encode(pa.array(texts[i : i + 300])) for i in range(0, len(texts), 300)]
        finally:
            tokenfiles.MEMORY = kept
        ids, n = np.concatenate([x[0] for x in got]), np.concatenate([x[1] for x in got])
        want = [known.encode(t or "", add_special_tokens=False).ids + [2] for t in texts]
        assert n.tolist() == [len(w) for w in want] and ids.tolist() == [i for w in want for i in w]


def test_a_document_longer_than_a_block(spark, tmp_path):
    path = public_tokenizers.path("word_bpe_49k.json")
    docs = spark.createDataFrame([(1, "one two three " * 400), (2, "four"), (None, "five six"), (3, "")], "doc_id long, text string")
    tokenfiles.write(docs, str(tmp_path / "ids"), path, block_ids=100, parts=3)
    rows = {r.doc_id: np.frombuffer(r.ids, "<u4") for r in tokenfiles.read(spark, str(tmp_path / "ids")).collect()}
    coder = tokenfiles.WordCoder(path)
    for r in docs.collect():
        assert rows[r.doc_id].tolist() == coder.encode(pa.array([r.text]))[0].tolist()


def test_html_extraction(spark, sf):
    page = """<!DOCTYPE html><html><head><title>No</title><style>p{}</style></head><body><header>Site name</header><nav><a href=x>Home</a></nav><div class="cookie-notice">We use cookies</div>
    <main><h1>The&nbsp;title &amp; more</h1><p>First  <b>bold</b>
    words of a longer paragraph here<p>Second one<script>var a="<p>no</p>"</script> goes on</p><form><label>Mail</label></form><ul><li>point one</li></ul></main>
    <section id="comments"><p>nice post, thank you</p></section><aside>Related things</aside><footer>&copy; us</footer></body></html>"""
    assert htmltext.extract(page, {}) == "The title & more\nFirst bold words of a longer paragraph here\nSecond one goes on\npoint one"
    assert htmltext.extract(None, {}) == htmltext.extract("", {}) == htmltext.extract("<nav>only menu</nav>", {}) == ""
    values = [random.Random(6).choice([-2.0, -1.0, 1.0, 3.0]) for _ in range(60)]
    a, b = htmltext.region(values)
    assert math.isclose(sum(values[a:b]), max(sum(values[i:j]) for i in range(60) for j in range(i, 61)))
    from corpuslab.llm.common import table

    pages = table(spark, sf, "pages")
    weights = htmltext.learn(pages)
    assert weights["-nav"] < 0 < weights["+article"]
    found = {r.page_id: r for r in htmltext.main_text(pages, weights).collect()}
    for p in pages.collect():
        assert found[p.page_id].text and "track(" not in found[p.page_id].text and "©" not in found[p.page_id].text
    odd = spark.createDataFrame([(None, None, None), (1, "u", ""), (1, "u", "")], "page_id long, url string, html string")
    assert [r.text for r in htmltext.main_text(odd, weights).collect()] == ["", "", ""]


ARTICLE = "<h1>The headline stands here</h1><p>" + "plain words of the main text " * 12 + "</p>"
MAIN_TEXT = "The headline stands here\n" + ("plain words of the main text " * 12).strip()


@pytest.mark.parametrize("page", [
    f"<html><head><title>No</title><body><nav>Menu</nav><article>{ARTICLE}</article></body></html>",
    f"<body><svg/><iframe/><nav>Menu</nav><article>{ARTICLE}</article>",
    f"<body><nav><a>Home</a></nav><div class='post-content share'>{ARTICLE}</div><div id='comments'><p>nice post</p></div></body>",
    f"<body><article><div class='article-header'>{ARTICLE.split('<p>')[0]}</div><p>{ARTICLE.split('<p>')[1]}</article><footer>us</footer>",
    f"<body><ul class='menu'><li>Home</ul><div>{ARTICLE}</div><div class=\"sidebar\"><p>more news today</p></div></body>",
    f"<body><div class='has-sidebar'><article>{ARTICLE}</article></div></body>",
    f"<body><p hidden title=\"abc></p><main>{ARTICLE}</main><aside>x</aside>",
    f"<body><noscript><article>{ARTICLE}</article>",
])
@pytest.mark.parametrize("learnt", [False, True])
def test_html_pages_that_are_odd(page, learnt):
    weights = {"div": htmltext.weight("div", 0, 1000), "<div": htmltext.weight("<div", 0, 1000), ".ad": -2.0} if learnt else {}
    got = htmltext.extract(page, weights)
    assert got == MAIN_TEXT


def test_html_weights_are_learnt_by_name(spark):
    words = "some words that stand in here " * 3
    page = f"<body><div class='qqz'><p>{words}</p></div><article><p>{words * 2}</p><div class='zzq'><p>{words}</p></div><div class=share>tell your friends</div></article></body>"
    pages = spark.createDataFrame([(i, "u", page) for i in range(30)] + [(99, None, None)], "page_id long, url string, html string")
    weights = htmltext.learn(pages)
    assert weights[".qqz"] < -1 and weights[".zzq"] > 0.5 and ".share" not in weights
    got = htmltext.extract(f"<body><div class='qqz'>{words}</div><div class='zzq'>{words}</div><div class='share'>tell</div></body>", weights)
    assert got == words.strip()
    assert htmltext.learn(pages.limit(0)) == {} and htmltext.main_text(pages.limit(0), weights).count() == 0
    long = "<article>" + "<p>word word</p>" * 60_000
    assert len(htmltext.extract(long, weights)) == 10 * 60_000 - 1


def test_cascade_is_exact(spark):
    universe = spark.range(6000).selectExpr("concat('key', id) key", "id % 9 = 0 listed")
    levels = urlfilter.build_cascade(universe)
    wrong = universe.withColumn("m", urlfilter.member(levels, universe.key)).where("m <> listed").count()
    assert wrong == 0 and len(levels) >= 2
    assert urlfilter.build_cascade(universe.where("not listed")) == []
    urls = [None, "", "nothing", "http://www.Casino-Win.example.com/en/1", "http://a.org/x", "https://x.example.org/es/1?q", "https://example.org/en/12", "//b.org/", "http://c.com", "http://c.com/de/#a", "http://evilorg/", "http://u@h.net:80?x"]
    pages = spark.createDataFrame([(i, u, 1) for i, u in enumerate(urls)] + [(None, urls[4], 2)], "page_id long, url string, host int")
    got = {r.page_id: r for r in urlfilter.judge(pages, urlfilter.block_list(spark)).collect()}
    assert (got[3].host, got[3].path, got[3].rule, got[3].verdict) == ("www.casino-win.example.com", "/en/1", None, "block")
    assert [got[i].verdict for i in (0, 1, 2, 4, 5, 6, 8, 9, 10)] == ["allow"] * 4 + ["block", "block", "allow", "block", "allow"]
    assert (got[11].host, got[11].path, got[5].rule, got[6].rule, got[8].rule) == ("u@h.net:80", "", "example.org/es/", "example.org/en/1", None)
    assert urlfilter.judge(pages.limit(0), urlfilter.block_list(spark)).count() == 0


def test_list_too_large_for_a_cascade_is_joined(spark):
    hosts = [f"h{i % 50}.d{i % 9}.example.com" for i in range(300)] + ["", None, "lone", "d3", "x.d3"]
    pages = spark.createDataFrame([(i, None if h is None else f"https://{h}/a", "x", 1, True) for i, h in enumerate(hosts)], "page_id long, url string, key string, salt int, blocked boolean")
    listed = spark.createDataFrame([("d3",), ("h7",), ("absent",), (None,), ("d3",)], "key string")
    assert urlfilter.build_cascade(spark.createDataFrame([("a", True), ("b", False)], "key string, listed boolean"), max_bits=0) is None
    ways = [sorted(map(str, urlfilter.judge(pages, listed, max_bits=bits).collect())) for bits in (urlfilter.MAX_BITS, 0)]
    assert ways[0] == ways[1] and len(ways[0]) == len(hosts)
    for r in urlfilter.judge(pages, listed, rules=()).collect():
        assert r.verdict == ("block" if {"d3", "h7"} & set(r.host.split(".")[:-1]) else "allow")
    assert {r.verdict for r in urlfilter.judge(pages, listed.limit(0), rules=()).collect()} == {"allow"}


def test_bpe_against_the_library(spark):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    known, mine = Tokenizer.from_file(path), bpe.load(path)
    rng = random.Random(8)
    alphabet = list(" \n\t  ab'sZ9.!é") + ["<|endoftext|>", "́", "\x1c", "\x85", "​", "\xa0", "　", "'ll", " the", "日", "💥"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 14))) for _ in range(3000)] + ["a" * 3000, " " * 50, "x " * 500]
    for t in texts:
        ids = known.encode(t, add_special_tokens=False).ids
        raw = mine.encode(t)
        assert np.frombuffer(raw, "<u4").tolist() == ids, repr(t)
        assert mine.decode(raw).decode() == known.decode(ids, skip_special_tokens=False)
    assert mine.decode(np.array([mine.byte_ids[0xE9]], "<u4").tobytes()).decode() == "�"
    docs = odd_documents(spark)
    rows = bpe.digest(docs, path).collect()
    assert len(rows) == docs.count() and bpe.digest(docs.limit(0), path).count() == 0
    coded = bpe.encode(docs, path)
    assert sorted(r.decoded for r in bpe.decode(coded, path).collect()) == sorted(r.text or "" for r in docs.collect())


def test_pipeline_on_odd_rows(spark, sf):
    import corpus_pipeline as p
    from corpuslab.llm.common import table

    docs = table(spark, sf, "documents")
    odd = docs.union(docs.limit(5)).union(spark.createDataFrame([(None, None, None, None, None), (9, "", "en", None, 0)], docs.schema))
    assert [n for n, _ in p.STAGES] == ["quality", "near_duplicates", "mixing", "bpe"]
    kept = p.quality_rules(spark, odd, sf).checkpoint()
    assert kept.columns == docs.columns and 0 < kept.count() < odd.count() and kept.where("text is null").count() == 0
    one = p.near_duplicates(spark, kept, sf).checkpoint()
    assert one.columns == docs.columns and one.count() == simhash.near_duplicates(kept).select("component_id").distinct().count()
    mixed = p.mix_sources(spark, one, sf).checkpoint()
    plan = {r.doc_id: r.taken // max(r.size, 1) for r in mixing.mix_sizes(one).collect() if r.size}
    seen = Counter(r.doc_id for r in mixed.select("doc_id").collect())
    assert mixed.columns == docs.columns and all(seen.get(k, 0) == n for k, n in plan.items())
    assert p.byte_pairs(spark, mixed, sf).count() == mixed.count()
    twice = one.union(one.limit(3))
    assert p.mix_sources(spark, twice, sf).count() > 0


CLASH = "_id _h _hash _n _size _copies _copy _rows _words _each kept n_words llr base_failed row copies rows size target source_size n each words hash h number count bucket rank shard slot fp component_id row_number root anchor".split()


def clashing(docs):
    """The documents with extra columns of names that a stage might use, each filled with its name."""
    from pyspark.sql import functions as F

    return docs.select("*", *[F.lit(c).alias(c) for c in CLASH])


def test_stages_keep_columns_of_any_name(spark, sf):
    import corpus_pipeline as p
    from corpuslab.llm.common import table

    plain = table(spark, sf, "documents")
    plain = plain.union(plain.limit(4))
    for _, stage in p.STAGES:
        wide = clashing(plain)
        want, got = stage(spark, plain, sf), stage(spark, wide, sf)
        if stage is p.STAGES[-1][1]:
            assert sorted(map(str, got.collect())) == sorted(map(str, want.collect()))
            assert stage(spark, wide.limit(0), sf).count() == 0
            break
        rows = got.collect()
        assert got.dtypes == wide.dtypes
        assert all(r[c] == c for r in rows for c in CLASH)
        assert sorted(str([r[c] for c in plain.columns]) for r in rows) == sorted(str(list(r)) for r in want.collect())
        empty = stage(spark, wide.limit(0), sf)
        assert empty.columns == wide.columns and empty.count() == 0
        plain = spark.createDataFrame(want.collect(), plain.schema)


def test_operators_answer_empty_tables_and_clashing_columns(spark, sf):
    from corpuslab.llm import queries as q
    from corpuslab.llm.common import table

    kept = q.table
    docs = odd_documents(spark)
    wide = clashing(docs.drop("shard", "size", "fp", "kept"))
    pages = spark.createDataFrame([(None, None, None), (1, "http://free-bets.example.com/a", "<p>" + "word " * 30)], "page_id long, url string, html string")
    try:
        for made, wide_pages in ((wide, clashing(pages)), (docs.select("doc_id", "text", "lang", "source", "n_chars"), pages)):
            for empty in (False, True):
                tables = {"documents": made, "pages": wide_pages}
                q.table = lambda s, d, n: (tables[n].limit(0) if empty else tables[n]) if n in tables else table(s, d, n)
                found = {k: sorted(map(str, f(spark, sf).collect())) for k, f in q.queries().items()}
                n = {k: 0 if empty else (wide_pages if k in ("op8_html_region", "op9_bloom_cascade") else made).count() for k in found}
                assert {k: len(v) for k, v in found.items()} == n
    finally:
        q.table = kept


def test_targets_of_many_sources(spark):
    rng = random.Random(4)
    rows = [(None if i == 3 else f"s{i:03}é", rng.choice([0, 1, 5, 100, 1000])) for i in range(60)]
    sizes = spark.createDataFrame(rows, "source string, source_size long")
    few = {r.source: r.target for r in mixing.plan_targets(sizes).collect()}
    many = {r.source: r.target for r in mixing.plan_targets(sizes, bound=0).collect()}
    assert few.keys() == many.keys() and all(math.isclose(few[k], many[k], rel_tol=1e-9, abs_tol=1e-9) for k in few)


def test_shards_hold_the_digests_and_places_of_their_rows(spark, sf):
    from corpuslab.llm.common import table

    docs = table(spark, sf, "documents").union(odd_documents(spark).selectExpr("doc_id", "text", "lang", "source", "n_chars"))
    rows = sharding.shard_documents(docs).collect()
    want = sorted((str(r.doc_id), len((r.text or "").encode()) + 8, zlib.crc32((r.text or "").encode())) for r in docs.collect())
    assert sorted((str(r.doc_id), r.size, r.text_crc32) for r in rows) == want
    n = len(rows)
    at = {sharding.locate(r.shard, r.slot, n, 24): (r.doc_id, r.text_crc32) for r in rows}
    numbered = sharding.number_rows(docs.selectExpr("doc_id", "crc32(encode(coalesce(text, ''), 'UTF-8')) text_crc32", "bigint(octet_length(coalesce(text, '')) + 8) size"), ["doc_id", "text_crc32", "size"]).collect()
    assert sorted(at) == list(range(n)) and all(at[r.row_number] == (r.doc_id, r.text_crc32) for r in numbered)


def test_media_columns_are_those_of_the_texts(spark):
    import hashlib

    docs = odd_documents(spark)
    texts = {r.doc_id: (r.text or "").encode() for r in docs.collect() if r.doc_id is not None}
    for r in ogg.digest(docs).where("doc_id is not null").collect():
        raw = texts[r.doc_id]
        payload = raw + b" " * (-len(raw) % 192 if raw else 192)
        media = ogg.mux(payload)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest())
        assert (r.tail_crc32, r.media_bytes, r.media_sha256) == (zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest()) and r.feature


def test_mix_takes_its_targets(spark):
    from corpuslab.llm.common import table

    docs = table(spark, "/root/testdata/sf0.01", "documents")  # enough documents for sums to come near any target
    texts = {r.doc_id: (r.source, len(words_of(r.text))) for r in docs.collect()}
    rows = mixing.mix_sizes(docs).collect()
    sizes = Counter()
    for source, n in texts.values():
        sizes[source] += n
    order = sorted(sizes)
    want = dict(zip(order, mixing.water_fill([sizes[s] for s in order], [(1, 2, 3)[i % 3] for i in range(len(order))])))
    taken = Counter()
    for r in rows:
        source, n = texts[r.doc_id]
        assert r.size == n and r.source_size == sizes[source] and math.isclose(r.target, want[source]) and r.taken <= 3 * n
        taken[source] += r.taken
    assert all(abs(taken[s] - want[s]) <= 1 for s in order)


def test_columns_of_contracts(spark, sf):
    from corpuslab.llm.queries import queries

    first = {k.split("_")[0]: f(spark, sf).columns for k, f in queries().items() if k.split("_")[0] in ("op1", "op2", "op5", "op6", "op9")}
    assert first["op1"][:8] == ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
    assert first["op2"] == ["doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard"]
    assert first["op6"] == ["doc_id", "size", "source_size", "target", "taken"]
    assert len(queries()) == 10


