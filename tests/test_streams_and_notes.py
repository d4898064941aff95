from pyspark.sql import functions as F

from bitempo.functions.timeaxis import DAY
from bitempo.memory import notes
from bitempo.operators import series
from bitempo.streaming import streams
from bitempo.substrate.log import assert_fact, correct_fact, operations

EDGE = "eid long, src long, dst long, t long, w double, etype string"


def test_file_stream_bursts_equal_batch(spark, tmp_path):
    counts = [(1, 1.0), (2, 2.0), (3, 1.0), (4, 2.0), (5, 9.0), (6, 1.0)]
    for i in range(0, 6, 2):
        spark.createDataFrame([("k", b, v) for b, v in counts[i : i + 2]], "key string, bucket long, value double").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("key string, bucket long, value double").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    streams.run_to_end(streams.burst_stream(stream, 4, 3.0), str(tmp_path / "out"), str(tmp_path / "c"))
    got = {r["bucket"]: (r["score"], r["is_burst"]) for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    batch = series.detect_bursts(spark.createDataFrame(counts, "bucket long, value double"), "zscore", 4, 3.0)
    wanted = {r["bucket"]: (r["score"], r["is_burst"]) for r in batch.collect()}
    assert {b: x[1] for b, x in got.items()} == {b: x[1] for b, x in wanted.items()} and abs(got[5][0] - wanted[5][0]) < 1e-6


def test_belief_ingest_is_idempotent_and_moves_on(spark, tmp_path):
    ingest = streams.BeliefIngest(spark, str(tmp_path / "log"))
    first = operations(spark, [assert_fact(1, "a", 0, 10, 1.0, phys=100), correct_fact(2, "a", 2, 4, 2.0, phys=50)])
    ingest(first, 0)
    ingest(first, 0)
    ingest(operations(spark, [assert_fact(3, "a", 0, 1, 3.0, phys=10)]), 1)
    times = [r["tt"] for r in ingest.log().orderBy("batch_id").collect()]
    assert len(times) == 3 and times == sorted(set(times)) and times[0] >= 100


def test_late_events_become_a_correction_batch(spark):
    df = spark.createDataFrame([(1, 0, 1, 5, 1.0, "e"), (2, 0, 1, 50, 1.0, "e")], EDGE)
    on_time, late = streams.route_late(df, 10, 77)
    assert [r["eid"] for r in on_time.collect()] == [2] and [(r["eid"], r["tt"]) for r in late.collect()] == [(1, 77)]


def test_stream_joins_and_sessions_plan(spark, tmp_path):
    spark.createDataFrame([(1, 0, 1, 10**15, 1.0, "e"), (2, 1, 0, 10**15 + 60_000_000, 1.0, "e")], EDGE).coalesce(1).write.parquet(str(tmp_path / "e"))
    edges = streams.edge_stream(spark, str(tmp_path / "e"))
    streams.run_to_end(streams.reply_pairs(edges, streams.edge_stream(spark, str(tmp_path / "e")), "1 hour"), str(tmp_path / "o"), str(tmp_path / "c"))
    assert [tuple(r) for r in spark.read.parquet(str(tmp_path / "o")).collect()] == [(1, 2)]
    assert streams.user_sessions(edges).isStreaming and streams.windowed_counts(edges, "2 days", "1 day").isStreaming


def test_notes_hold_checked_numbers_only(spark):
    edges = spark.createDataFrame([(i, i % 3, 5, i * DAY, 1.0, "e") for i in range(20)], EDGE)
    made = notes.write_notes(notes.weekly_facts(edges), 100)
    assert notes.admitted(made).count() == made.count() == 3
    assert notes.admitted(made.withColumn("text", F.concat("text", F.lit(" About 12345 more.")))).count() == 0


def test_a_later_correction_withdraws_notes_it_overlaps(spark):
    edges = spark.createDataFrame([(i, 0, 5, i * DAY, 1.0, "e") for i in range(21)], EDGE)
    made = notes.write_notes(notes.weekly_facts(edges), 100)
    change = operations(spark, [correct_fact(1, "a", 8 * DAY, 9 * DAY, 1.0)]).withColumn("tt", F.lit(150))
    for f in (notes.quarantine, notes.quarantine_any):
        assert [r["window_s"] for r in f(made, change).where("quarantined").collect()] == [7 * DAY]
        assert f(made, change.withColumn("tt", F.lit(50))).where("quarantined").count() == 0
    assert notes.citable(notes.quarantine(made, change)).count() == made.count() - 1


def test_ingest_decides_outcomes_from_what_is_believed(spark, tmp_path):
    ingest = streams.BeliefIngest(spark, str(tmp_path / "log"))
    ingest(operations(spark, [correct_fact(1, "a", 2, 4, 2.0, phys=10), assert_fact(2, "b", 0, 10, 1.0, phys=11)]), 0)
    ingest(operations(spark, [correct_fact(3, "b", 2, 4, 2.0, phys=20), correct_fact(4, "a", 2, 4, 2.0, phys=21)]), 1)
    again = streams.BeliefIngest(spark, str(tmp_path / "log"))  # a restarted writer
    again(operations(spark, [correct_fact(3, "b", 2, 4, 2.0, phys=20), correct_fact(4, "a", 2, 4, 2.0, phys=21)]), 1)
    again(operations(spark, [correct_fact(5, "b", 20, 24, 2.0, phys=30), correct_fact(6, "b", 3, 5, 7.0, phys=31)]), 2)
    got = {r["batch_id"]: (r["outcome"], r["fail_code"]) for r in again.log().collect()}
    failed = ("failed", "F_NOTHING_TO_CORRECT")
    assert got == {1: failed, 2: ("committed", None), 3: ("committed", None), 4: failed, 5: failed, 6: ("committed", None)} and again.log().count() == 6
    pieces = sorted((r["vt_s"], r["vt_e"], r["w"]) for r in again.believed.read(again.believed.epochs()[-1:]).collect())
    assert pieces == [(0, 2, 1.0), (2, 3, 2.0), (3, 5, 7.0), (5, 10, 1.0)]


def test_arrivals_go_on_after_a_restart(spark, tmp_path):
    batch = lambda *rows: spark.createDataFrame([(*r, 1.0, "e") for r in rows], EDGE)
    first = streams.ArrivalState(spark, 0, 0, folder=str(tmp_path / "s"))
    first(batch((1, 0, 1, 5), (2, 1, 2, 6)), 0)
    second = streams.ArrivalState(spark, 0, 0, folder=str(tmp_path / "s"))
    for _ in range(2):  # the epoch is repeated
        second(batch((3, 2, 3, 9), (4, 9, 4, 9)), 1)
    assert {r["node"]: r["first"] for r in second.state.collect()} == {0: 0, 1: 5, 2: 6, 3: 9}


def test_an_open_correction_withdraws_the_notes_after_it(spark):
    edges = spark.createDataFrame([(i, 0, 5, i * DAY, 1.0, "e") for i in range(21)], EDGE)
    made = notes.write_notes(notes.weekly_facts(edges), 100)
    change = operations(spark, [correct_fact(1, "a", 8 * DAY, 1 << 62, 1.0)]).withColumn("tt", F.lit(150))
    for f in (notes.quarantine, notes.quarantine_any):
        assert sorted(r["window_s"] for r in f(made, change).where("quarantined").collect()) == [7 * DAY, 14 * DAY]
