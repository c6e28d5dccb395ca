"""Streams give the integers that a batch gives; retries and late rows are handled."""

import pytest
from conftest import SF
from pyspark.sql import functions as F

from privfreq.functions import sql
from privfreq.params import SMALL
from privfreq.sources import sinks, tables, zipf_source
from privfreq.streaming import windows


@pytest.fixture()
def files(spark, tmp_path):
    """Events in time order, in three files; the second is there twice (a retry)."""
    rows = tables.load(spark, SF, "events")
    cuts = [r["ts"] for r in rows.select("ts").orderBy("ts").collect()]
    a, b = cuts[len(cuts) // 3], cuts[2 * len(cuts) // 3]
    out = tmp_path / "events"
    for i, part in enumerate((rows.where(F.col("ts") < a), rows.where((F.col("ts") >= a) & (F.col("ts") < b)), rows.where((F.col("ts") >= a) & (F.col("ts") < b)), rows.where(F.col("ts") >= b))):
        part.coalesce(1).write.mode("append").parquet(str(out))
    return str(out)


def run(stream, name, mode="append"):
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    try:
        query.awaitTermination(120)
        assert query.exception() is None
    finally:
        query.stop()
    return query


def test_stream_equals_batch(spark, files):
    run(windows.stream_sketch(windows.stream_events(spark, files, 10), SMALL, lateness="60 days"), "st", "complete")
    got = {tuple(r) for r in spark.table("st").collect()}
    events = tables.load(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    assert got == {tuple(r) for r in windows.window_sketch(windows.event_reports(events, SMALL)).collect()}


def test_append_closes_windows(spark, files):
    run(windows.stream_sketch(windows.stream_events(spark, files, 10), SMALL, lateness="1 day"), "closed")
    assert spark.table("closed").count() > 0


def test_budget_of_a_user(spark, files):
    rows = windows.event_reports(windows.stream_events(spark, files, 10), SMALL)
    try:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
        run(windows.limited_reports(rows, 2), "spent", "append")
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    assert spark.table("spent").groupBy("user_id").count().agg(F.max("count")).first()[0] <= 2


def test_late_rows_are_counted(spark, files, tmp_path):
    """A file of old events after the newest ones: beyond the watermark, so they are dropped and reported."""
    rows = tables.load(spark, SF, "events")
    source = tmp_path / "late"
    for i, part in enumerate((rows.orderBy(F.desc("ts")).limit(100), rows.orderBy(F.desc("ts")).limit(50), rows.orderBy("ts").limit(40))):
        part.coalesce(1).write.mode("append").parquet(str(source))
    stream = windows.window_sketch(windows.event_reports(windows.stream_events(spark, str(source)), SMALL).withWatermark("ts", "1 hour"))
    query = run(stream, "late", "append")
    assert windows.watermark_losses(query) > 0


def test_update_mode_ends_at_the_batch_state(spark, files, tmp_path):
    """Every micro-batch writes the windows that it changed; the last value of each is the batch state's."""
    stream = windows.stream_sketch(windows.stream_events(spark, files, 1), SMALL, lateness="60 days")
    query = sinks_query(stream, tmp_path)
    got = {}
    for r in spark.read.parquet(str(tmp_path / "out")).orderBy("batch").collect():
        got[(r["start"], r["j"], r["l"])] = (r["signed_sum"], r["reports"])
    assert query.exception() is None
    events = tables.load(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    want = {(r["start"], r["j"], r["l"]): (r["signed_sum"], r["reports"]) for r in windows.window_sketch(windows.event_reports(events, SMALL)).collect()}
    assert got == want


def sinks_query(stream, tmp_path):
    query = windows.save_batches(stream, str(tmp_path / "out"), str(tmp_path / "checkpoint"))
    try:
        query.awaitTermination(180)
    finally:
        query.stop()
    return query


def test_stream_joins_a_static_score_table(spark, files):
    scores = spark.createDataFrame([("click", 9.0), ("view", 2.0)], "item string, g double")
    run(windows.scored_stream(windows.stream_events(spark, files, 10), scores, 5.0), "scored_events", "append")
    got = {(r["item"], r["g"], r["heavy"]) for r in spark.table("scored_events").select("item", "g", "heavy").distinct().collect()}
    items = {r["event_type"] for r in tables.load(spark, SF, "events").select("event_type").distinct().collect()}
    listed = {"click": 9.0, "view": 2.0}
    assert got == {(i, listed.get(i, 0.0), listed.get(i, 0.0) >= 5.0) for i in items}


def test_reports_join_their_acknowledgements(spark, files, tmp_path):
    """Two streams: of the acknowledged events only those answered within the hour come out."""
    events = tables.load(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    some = events.where("event_id % 3 = 0").select(F.col("event_id").cast("string").alias("rid"), (F.col("ts") + F.expr("interval 1 minute") * F.when(F.col("event_id") % 2 == 0, 30).otherwise(90)).alias("ack_ts"))
    some.coalesce(1).write.parquet(str(tmp_path / "acks"))
    acks = spark.readStream.schema("rid STRING, ack_ts TIMESTAMP").parquet(str(tmp_path / "acks"))
    rows = windows.event_reports(windows.stream_events(spark, files, 10), SMALL).dropDuplicates(["rid"])
    run(windows.acknowledged(rows, acks, lateness="90 days"), "acknowledged", "append")
    assert {r["rid"] for r in spark.table("acknowledged").collect()} == {str(r["event_id"]) for r in events.where("event_id % 6 = 0").collect()}


def test_sessions(spark):
    events = tables.load(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    assert windows.session_reports(events).agg(F.sum("n")).first()[0] == 1000


def test_zipf_source(spark):
    zipf_source.register(spark)
    df = spark.read.format("zipf_items").option("s", 1.3).option("rows", 5000).option("n_ids", 1000).load()
    assert df.count() == 5000 and df.agg(F.max("item")).first()[0] <= 1000
    assert df.groupBy("item").count().orderBy(F.desc("count")).first()["item"] == 1


def test_state_round_trip(spark, tmp_path):
    state = spark.createDataFrame([(0, 1, 5, 9)], "j int, b int, plus bigint, reports bigint")
    sinks.save_state(state, str(tmp_path / "s"), "r1", 1)
    sinks.save_state(state, str(tmp_path / "s"), "r1", 2)
    assert [tuple(r) for r in sinks.load_state(spark, str(tmp_path / "s"), "r1", 2).collect()] == [(0, 1, 5, 9)]


def test_formats(spark, tmp_path):
    rows = tables.types(spark, SF).limit(20)
    for fmt in ("csv", "json", "orc", "parquet"):
        rows.write.format(fmt).save(str(tmp_path / fmt))
        assert tables.load_items(spark, str(tmp_path / fmt), fmt, "rid STRING, item STRING, key BIGINT").count() == 20


def test_sql_surface(spark):
    sql.register(spark, SMALL)
    a, b = SMALL.hashes()[0]
    assert spark.sql(f"SELECT pf_bucket(5, {a}, {b}, 64) AS x").first()["x"] == (a * 5 + b) % 2147483647 % 64
    assert spark.sql("SELECT count(*) AS n FROM probe_rows(5)").first()["n"] == SMALL.k
    assert [r["bit"] for r in spark.sql("SELECT * FROM encode_bits(2, 6)").collect()] == [-1, -1, 1, -1, -1, -1]
    sql.publish(spark.createDataFrame([("a", 1.0)], "item string, f_hat double"), "split")
    assert spark.sql("SELECT f_hat FROM freq_split WHERE item = 'a'").first()["f_hat"] == 1.0


def test_packed_reports_round_trip(spark):
    from privfreq.operators import reports

    p = SMALL.but(m=20, k=3)
    bits = reports.one_hot_bits(tables.types(spark, SF).limit(30), p)
    packed = sinks.pack_bits(bits, 20)
    assert packed.agg(F.max(F.length("bits"))).first()[0] == 3
    assert sorted(map(tuple, sinks.unpack_bits(packed, 20).collect())) == sorted(map(tuple, bits.collect()))
