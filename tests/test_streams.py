"""Streams call the library and are held against its batch twins or against loops."""

from datetime import datetime, timedelta

from pyspark.sql import functions as F

from corpuslab.streaming import telemetry as S

START = datetime(2024, 1, 1)
SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double"


def rows_of(minutes):
    return [(i, START + timedelta(minutes=m), u, kind, float(i)) for i, (m, u, kind) in enumerate(minutes)]


def replay(spark, folder, parts, make, mode="append"):
    """Feeds ``parts`` file by file and gives the rows that came out and the last progress reports."""
    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, SCHEMA).coalesce(1).write.parquet(f"{folder}/in/part={i}")
    stream = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(f"{folder}/in/*")
    name = "t" + folder.rsplit("/", 1)[-1].replace("-", "_")
    query = make(stream).writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{folder}/c").trigger(availableNow=True).start()
    query.awaitTermination(240)
    return spark.table(name).collect(), query.recentProgress


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    first = rows_of([(0, 1, "view"), (200, 1, "view")])
    late = [(90, START + timedelta(minutes=5), 1, "view", 1.0), (91, START + timedelta(minutes=205), 1, "view", 1.0)]
    between = [(80, START + timedelta(minutes=206), 1, "view", 1.0)]  # rows are held against the watermark before the last one
    rows, progress = replay(spark, str(tmp_path), [first, between, late, rows_of([(600, 1, "view")])], S.tumbling)
    dropped = sum(o["numRowsDroppedByWatermark"] for p in progress for o in p["stateOperators"])
    got = {r.start: r.n for r in rows}
    assert dropped == 1 and got[START] == 1 and got[START + timedelta(minutes=180)] == 3


def test_output_modes_agree_with_the_batch(spark, tmp_path):
    part = [rows_of([(m * 7, m % 3, "error" if m % 4 == 0 else "view") for m in range(60)])]
    batch = {(r.start, r.n, r.faults) for r in S.sliding_faults(spark.createDataFrame(part[0], SCHEMA)).collect()}
    for mode in ("update", "complete"):
        (tmp_path / mode).mkdir()
        rows, _ = replay(spark, str(tmp_path / mode), part, S.sliding_faults, mode)
        assert {(r.start, r.n, r.faults) for r in rows} == batch


def test_a_restart_goes_on_from_the_checkpoint(spark, tmp_path):
    seen = []
    for i in (0, 1):
        spark.createDataFrame(rows_of([(i * 10, i, "view")]), SCHEMA).write.mode("append").parquet(str(tmp_path / "in"))
        stream = spark.readStream.schema(SCHEMA).parquet(str(tmp_path / "in"))
        S.run_once(stream, str(tmp_path / "out"), str(tmp_path / "c"))
        seen.append(spark.read.parquet(str(tmp_path / "out")).count())
    assert seen == [1, 2]


def test_recoveries_of_two_streams(spark, tmp_path):
    part = rows_of([(0, 1, "error"), (10, 1, "view"), (20, 2, "view"), (50, 1, "view"), (60, 2, "error"), (200, 2, "view")])
    rows, _ = replay(spark, str(tmp_path), [part], S.recoveries)
    assert [(r.fault, r.next) for r in rows] == [(r.fault, r.next) for r in S.recoveries(spark.createDataFrame(part, SCHEMA)).collect()] == [(0, 1)]


def test_drains_against_a_loop(spark, tmp_path):
    one = rows_of([(0, 1, "error"), (5, 1, "error"), (9, 1, "view"), (10, 2, "error"), (12, 3, "view")])
    two = [(i + 50, *r[1:]) for i, r in enumerate(rows_of([(100, 2, "view"), (110, 3, "error"), (150, 4, "view")]))]
    three = [(i + 80, *r[1:]) for i, r in enumerate(rows_of([(600, 4, "view")]))]
    rows, _ = replay(spark, str(tmp_path), [one, two, three], S.drains)
    at = lambda m: START + timedelta(minutes=m)
    want = {(1, at(0), at(9), 2, "restarted"), (2, at(10), at(40), 1, "expired"), (3, at(110), at(140), 1, "expired")}
    assert {tuple(r) for r in rows} == want and len(rows) == 3


def test_distinct_documents_and_labels(spark, tmp_path):
    docs = spark.createDataFrame([(i, t, START) for i, t in enumerate(["a", "b", "a", ""])], "doc_id long, text string, arrived timestamp")
    docs.write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(docs.schema).parquet(str(tmp_path / "in"))
    labels = spark.createDataFrame([(1, 0)], "doc_id long, quality int")
    S.run_once(S.with_labels(S.distinct_documents(stream), labels), str(tmp_path / "out"), str(tmp_path / "c"))
    got = spark.read.parquet(str(tmp_path / "out"))
    assert got.count() == S.distinct_documents(docs).count() == 3 and got.where(F.col("text") == "b").first().quality == 0
