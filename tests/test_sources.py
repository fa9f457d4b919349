import pytest

from corpuslab.functions.register import register_all
from corpuslab.operators import sftset
from corpuslab.sources.html import pages_as_documents
from corpuslab.sources.shards import read_shards, write_examples, write_shards
from corpuslab.tables import load


def test_shards_round_trip_and_fingerprint(spark, tmp_path):
    rows = [(s, q, [s, q, 65_535, 0]) for s in range(2) for q in range(3)]
    packed = spark.createDataFrame(rows, "shard int, seq long, ids array<int>")
    write_shards(packed, str(tmp_path / "x"), "abc")
    assert sorted((r.shard, r.seq, r.ids) for r in read_shards(spark, str(tmp_path / "x"), "abc").collect()) == rows
    with pytest.raises(Exception, match="packed with"):
        read_shards(spark, str(tmp_path / "x"), "other").collect()
    with pytest.raises(Exception, match="16 bits"):
        write_shards(spark.createDataFrame([(0, 0, [65_536])], "shard int, seq long, ids array<int>"), str(tmp_path / "y"), "abc")


def test_sql_functions_and_examples(spark, sf, tmp_path):
    register_all(spark)
    r = spark.sql("SELECT round(z_over_chance(0.306D, 900, 4), 2) z, round(wilson_low(5, 8), 3) a, round(wilson_high(5, 8), 3) b, wilson_high(9, 9) c").first()
    assert tuple(r) == (3.65, 0.306, 0.863, 1.0)
    write_examples(sftset.build_set(load(spark, sf, "conversations"), "v3"), str(tmp_path / "sft"))
    assert set(spark.read.json(str(tmp_path / "sft")).columns) >= {"conv_id", "segments", "condition"}
    docs = pages_as_documents(load(spark, sf, "pages"))
    assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"] and docs.where("text = ''").count() == 0
