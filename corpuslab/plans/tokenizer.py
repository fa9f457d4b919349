"""Queries on pre-tokenization, fertility, BPE and packing."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import pretokenize as P
from ..functions import views as V
from ..operators import bpe
from ..tables import load, shared_folder
from .registry import query

VIEWS = {"nfc": ("text", lambda c: c), "nfd": (V.sql_decomposed("text"), V.decomposed_view), "abugida": (V.sql_abugida("text"), V.abugida_view)}
_CLASS = {"letters": r"\p{L}", "letters_marks": r"\p{L}\p{M}"}


def _n(pattern: str, text: str = "text") -> str:
    return f"len(regexp_extract_all({text}, '{pattern}'))"


def _docs(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id", "lang", "text")


@query(rf"SELECT lang, count(*) AS docs, sum(length(text))::bigint AS chars, sum(strlen(text))::bigint AS bytes, sum({_n(chr(92) + 'S+')})::bigint AS words FROM documents GROUP BY lang")
def tok_words_chars_bytes(spark, sf_dir):
    t = F.col("text")
    return _docs(spark, sf_dir).groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.length(t)).cast("long").alias("chars"), F.sum(F.octet_length(t)).cast("long").alias("bytes"), F.sum(P.n_words(t)).alias("words"))


def _fragmentation(view: str):
    text, make = VIEWS[view]
    sql = " UNION ALL ".join(rf"SELECT lang, '{r}' AS rule, sum({_n(chr(92) + 'S+')})::bigint AS words, sum({_n('[' + c + ']+', text)})::bigint AS pieces, round(sum({_n('[' + c + ']+', text)})::double / sum({_n(chr(92) + 'S+')}), 6) AS ratio FROM documents GROUP BY lang" for r, c in _CLASS.items())

    def run(spark, sf_dir):
        """Both rules' pieces from one scan, as two pairs of columns turned into rows."""
        v = make(F.col("text"))
        sums = _docs(spark, sf_dir).groupBy("lang").agg(F.sum(P.n_words(F.col("text"))).alias("words"), *[F.sum(P.n_pieces(v, r)).alias(r) for r in _CLASS])
        rows = sums.unpivot(["lang", "words"], list(_CLASS), "rule", "pieces")
        return rows.withColumn("ratio", F.round(F.col("pieces") / F.col("words"), 6))

    query(sql, name=f"tok_fragmentation_{view}")(run)


for _view in VIEWS:
    _fragmentation(_view)


@query(rf"""SELECT lang, round(sum({_n('[' + _CLASS['letters'] + ']+', VIEWS['abugida'][0])})::double / sum({_n('[' + _CLASS['letters_marks'] + ']+', VIEWS['abugida'][0])}), 6) AS abugida_gain,
round(sum({_n('[' + _CLASS['letters'] + ']+', VIEWS['nfd'][0])})::double / sum({_n('[' + _CLASS['letters_marks'] + ']+', VIEWS['nfd'][0])}), 6) AS nfd_gain FROM documents GROUP BY lang""")
def tok_fragmentation_gain(spark, sf_dir):
    def gain(view):
        v = VIEWS[view][1](F.col("text"))
        return F.round(F.sum(P.n_pieces(v, "letters")) / F.sum(P.n_pieces(v, "letters_marks")), 6).alias(f"{view}_gain")

    return _docs(spark, sf_dir).groupBy("lang").agg(gain("abugida"), gain("nfd"))


def _visible(rule: str, text: str) -> str:
    c = _CLASS[rule]
    return _n(rf"''(?:s|t|re|ve|m|ll|d)| ?[{c}]+| ?\p{{N}}+| ?[^\s\p{{N}}{c}]+", text)


@query(" UNION ALL ".join(rf"SELECT lang, '{r}' AS rule, sum({_n(chr(92) + 'S+')})::bigint AS words, sum({_visible(r, VIEWS['abugida'][0])})::bigint AS pieces, round(sum({_visible(r, VIEWS['abugida'][0])})::double / sum({_n(chr(92) + 'S+')}), 6) AS floor FROM documents GROUP BY lang" for r in _CLASS))
def tok_fertility_floor(spark, sf_dir):
    seen = _docs(spark, sf_dir).withColumn("text", V.abugida_view(F.col("text")))
    parts = [P.fertility_floor(seen, ["lang"], r).withColumn("rule", F.lit(r)) for r in _CLASS]
    return parts[0].unionByName(parts[1]).select("lang", "rule", "words", "pieces", "floor")


@query(rf"SELECT count(*) AS differing FROM documents WHERE regexp_extract_all(text, '[\p{{L}}]+') <> regexp_extract_all(text, '[\p{{L}}\p{{M}}]+')")
def tok_rule_difference(spark, sf_dir):
    return P.rule_difference(_docs(spark, sf_dir)).agg(F.count(F.lit(1)).alias("differing"))


_PIECE = r"''(?:s|t|re|ve|m|ll|d)| ?[\p{L}\p{M}]+| ?\p{N}+| ?[^\s\p{N}\p{L}\p{M}]+|\s+"


@query(rf"""WITH p AS (SELECT lang, unnest(regexp_extract_all(text, '{_PIECE}')) AS piece FROM documents), c AS (SELECT lang, piece, count(*) AS cnt FROM p GROUP BY ALL)
SELECT lang, piece, cnt, r::int AS r FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY cnt DESC, piece) AS r FROM c) WHERE r <= 20""")
def tok_piece_histogram_top(spark, sf_dir):
    from pyspark.sql import Window

    hist = P.piece_histogram(_docs(spark, sf_dir), "letters_marks", ["lang"])
    return hist.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("cnt"), "piece"))).where("r <= 20").select("lang", "piece", "cnt", "r")


@query(rf"SELECT lang, sum({_n(chr(92) + 'S+')})::bigint AS space, sum(length(text))::bigint AS char, sum(strlen(text))::bigint AS byte FROM documents GROUP BY lang")
def tok_baseline_units(spark, sf_dir):
    return _docs(spark, sf_dir).groupBy("lang").agg(*[F.sum(F.size(P.pretokenize(F.col("text"), r))).cast("long").alias(r) for r in ("space", "char", "byte")])


@query(rf"""WITH p AS (SELECT unnest(regexp_extract_all(text, '[\p{{L}}\p{{M}}]+')) AS piece FROM documents), c AS (SELECT piece, count(*) AS cnt FROM p GROUP BY piece),
pairs AS (SELECT substr(piece, i::int, 1) AS a, substr(piece, i::int + 1, 1) AS b, cnt FROM (SELECT piece, cnt, unnest(range(1, length(piece))) AS i FROM c))
SELECT a, b, sum(cnt)::bigint AS n FROM pairs GROUP BY a, b ORDER BY n DESC, a, b LIMIT 50""")
def tok_pair_counts_round1(spark, sf_dir):
    """The first round of merging, over distinct pieces and their counts."""
    pieces = _docs(spark, sf_dir).select(F.explode(F.regexp_extract_all("text", F.lit(r"[\p{L}\p{M}]+"), F.lit(0))).alias("piece")).groupBy("piece").agg(F.count(F.lit(1)).alias("cnt"))
    at = pieces.where(F.length("piece") > 1).select("piece", "cnt", F.explode(F.sequence(F.lit(1), F.length("piece") - 1)).alias("i"))
    pairs = at.select(F.substring("piece", F.col("i"), F.lit(1)).alias("a"), F.substring("piece", F.col("i") + 1, F.lit(1)).alias("b"), "cnt")
    return pairs.groupBy("a", "b").agg(F.sum("cnt").alias("n")).orderBy(F.desc("n"), "a", "b").limit(50)


@query()
def tok_bpe_fertility(spark, sf_dir):
    """Tokens for each word by language and rule, on the marked script, with tokenizers of the same size."""
    seen = _docs(spark, sf_dir).withColumn("text", V.abugida_view(F.col("text")))
    shared_folder(spark)
    out = None
    for rule in _CLASS:
        hist = P.piece_histogram(seen, rule, ["lang"]).checkpoint()
        merges = bpe.train_bpe(hist.groupBy("piece").agg(F.sum("cnt").alias("cnt")), bpe.BASE + 300)
        part = bpe.fertility(seen, merges, rule, ["lang"], hist=hist).withColumn("rule", F.lit(rule))
        out = part if out is None else out.unionByName(part)
    return out


@query()
def tok_mixture_sweep(spark, sf_dir):
    """English beside Spanish seen through the marked script: fertility, floor and slack by rule and share."""
    docs = _docs(spark, sf_dir).where("lang in ('en', 'es')")
    lrl = F.col("lang") == "es"
    seen = docs.withColumn("text", F.when(lrl, V.abugida_view(F.col("text"))).otherwise(F.col("text")))
    return bpe.mixture_sweep(seen, lrl, [0.25, 0.5, 1.0], list(_CLASS), bpe.BASE + 800)


@query()
def tok_fertility_gain(spark, sf_dir):
    """Fertility of the broken rule over that of the fixed one."""
    told = tok_bpe_fertility(spark, sf_dir).groupBy("lang").pivot("rule", list(_CLASS)).agg(F.first("fertility"))
    return told.withColumn("gain", F.round(F.col("letters") / F.col("letters_marks"), 6))


@query()
def tok_compare(spark, sf_dir):
    """Tokens for each word of several tokenizers on one text, ranked."""
    from pyspark.sql import Window

    shared_folder(spark)
    docs, t = _docs(spark, sf_dir), F.col("text")
    sums = docs.select(F.sum(P.n_words(t)).alias("words"), F.sum(F.length(t)).cast("long").alias("char"), F.sum(F.octet_length(t)).cast("long").alias("byte"))
    rows = sums.unpivot(["words"], ["char", "byte"], "tokenizer", "tokens")
    hist = P.piece_histogram(docs, "letters_marks").checkpoint()
    most = bpe.train_bpe(hist, bpe.BASE + 400)
    for size in (100, 400):  # the smaller one is the larger one's beginning
        tokens = hist.agg(F.sum(F.col("cnt") * bpe.token_count(bpe.Merges(most.pairs[:size]))("piece")).alias("tokens"))
        rows = rows.unionByName(sums.select("words").crossJoin(tokens).select("words", F.lit(f"bpe_{size}").alias("tokenizer"), "tokens"))
    told = rows.withColumn("fertility", F.round(F.col("tokens") / F.col("words"), 6))
    return told.withColumn("place", F.rank().over(Window.partitionBy(F.lit(0)).orderBy("fertility")))


@query(f"""WITH t AS (SELECT len(regexp_extract_all(text, '\\S+')) + 1 AS n, {V.sql_bucket('shard', 'doc_id')} % 8 AS shard FROM documents), s AS (SELECT shard, sum(n)::bigint AS total FROM t GROUP BY shard)
SELECT shard::int AS shard, seq::bigint AS seq, least(4096, total - seq * 4096)::bigint AS tokens FROM (SELECT shard, total, unnest(range(0, (total + 4095) // 4096)) AS seq FROM s)""")
def tok_pack_sequences(spark, sf_dir):
    """White-space tokens (their md5 numbers stand for ids) in sequences of 4096."""
    ids = F.transform(P.pretokenize(F.col("text"), "space"), lambda w: F.pmod(F.crc32(w.cast("binary")), F.lit(65_535)).cast("int") + 1)
    packed = bpe.pack(_docs(spark, sf_dir).select("doc_id", ids.alias("ids")), 4096)
    return packed.select("shard", "seq", F.size("ids").cast("long").alias("tokens"))


@query("SELECT count(*) AS docs, sum(len(regexp_extract_all(text, '\\S+')))::bigint AS tokens, sum(2 * len(regexp_extract_all(text, '\\S+')))::bigint AS bytes, 0::bigint AS refused FROM documents")
def tok_u16_shards(spark, sf_dir):
    """Ids in 16 bits: bytes of the serialised form, and rows whose ids don't come back."""
    ids = F.transform(P.pretokenize(F.col("text"), "space"), lambda w: F.pmod(F.crc32(w.cast("binary")), F.lit(65_536)).cast("int"))
    told = _docs(spark, sf_dir).select(ids.alias("ids")).withColumn("data", bpe.to_u16(F.col("ids")))
    return told.agg(F.count(F.lit(1)).alias("docs"), F.sum(F.size("ids")).cast("long").alias("tokens"), F.sum(F.octet_length("data")).cast("long").alias("bytes"), F.count_if(bpe.from_u16(F.col("data")) != F.col("ids")).alias("refused"))
