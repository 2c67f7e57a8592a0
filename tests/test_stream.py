"""Streams: a maintained map equals the batch, deletions subtract, late rows and repeats are handled."""

from datetime import datetime

from pyspark.sql import functions as F

from cellcount.operators.engine import evaluate_batch
from cellcount.plans.model import CountQuery, compare
from cellcount.sources.catalog import load
from cellcount.streaming import maintain as S
from tests.conftest import TINY

QS = [CountQuery.build("a", ["events"], (), [("events.event_type", compare("=", "click"))]), CountQuery.build("b", ["events"], (), [("events.value", compare(">=", 50.0))])]


def _parts(spark, tmp_path, n=4):
    e = load(spark, TINY)["events"]
    for k in range(n):
        e.where(F.col("event_id") % n == k).coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    return str(tmp_path)


def test_maintained_map_equals_batch(spark, tmp_path):
    sf = _parts(spark, tmp_path)
    state = S.MapState(spark, QS, load(spark, TINY), str(tmp_path / "state"))
    got = S.maintain(S.stream_of(spark, sf, "events"), state, str(tmp_path / "chk"))
    want = evaluate_batch(spark, QS, load(spark, TINY))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    # Nothing new: a second run changes nothing, and a batch that runs again replaces itself.
    again = S.maintain(S.stream_of(spark, sf, "events"), state, str(tmp_path / "chk"))
    assert sorted(map(tuple, again.collect())) == sorted(map(tuple, want.collect()))


def test_compacted_maps_count_alike(spark, tmp_path):
    rows = load(spark, TINY)["events"]
    state = S.MapState(spark, QS, load(spark, TINY), str(tmp_path / "state"))
    assert [r["n"] for r in state.counts().collect()] == [0, 0]
    for k in range(3):
        state.apply(rows.where(f"event_id % 4 = {k}"), k)
    state.compact()
    state.compact()
    state.apply(rows.where("event_id % 4 = 3"), 3)
    want = sorted(map(tuple, evaluate_batch(spark, QS, load(spark, TINY)).collect()))
    assert sorted(map(tuple, state.counts().collect())) == want
    state.compact()
    assert sorted(map(tuple, state.counts().collect())) == want
    assert len([p for p in (tmp_path / "state").rglob("_SUCCESS")]) == 1


def test_join_state_takes_batches_of_any_table(spark, tmp_path):
    from cellcount.plans import workloads as W

    t, qs = load(spark, TINY), W.of_pattern("co+ce", 4)
    state = S.JoinState(spark, qs, t, str(tmp_path))
    assert [r["n"] for r in state.counts().collect()] == [0] * 4
    parts = [(n, k) for k in range(2) for n in ("events", "customer", "orders")]
    key = {"events": "event_id", "customer": "c_custkey", "orders": "o_orderkey"}
    for i, (n, k) in enumerate(parts):
        state.apply(n, t[n].where(F.col(key[n]) % 2 == k), i)
    state.apply("orders", t["orders"].where("o_orderkey % 2 = 1"), len(parts) - 1)
    assert sorted(map(tuple, state.counts().collect())) == sorted(map(tuple, evaluate_batch(spark, qs, t).collect()))


def test_window_maps_equal_raw_counts(spark, tmp_path):
    s = S.stream_of(spark, TINY, "events").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    got = S.window_counts(S.complete(S.window_maps(s, QS, F.window("ts", "1 day")), str(tmp_path)), QS)
    rows = load(spark, TINY)["events"].withColumn("ts", F.col("ts").cast("timestamp"))
    want = S.windowed_counts(rows, QS, F.window("ts", "1 day"))
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0


def test_deletions_subtract(spark, tmp_path):
    rows = load(spark, TINY)["events"].withColumn("change", F.lit(1))
    state = S.MapState(spark, QS, load(spark, TINY), str(tmp_path / "state"), change="change")
    state.apply(rows, 0)
    state.apply(rows.where("event_id % 3 = 0").withColumn("change", F.lit(-1)), 1)
    left = evaluate_batch(spark, QS, {"events": rows.where("event_id % 3 <> 0").drop("change")})
    assert sorted(map(tuple, state.counts().collect())) == sorted(map(tuple, left.collect()))


def test_new_constants_need_new_scales(spark, tmp_path):
    state = S.MapState(spark, QS, load(spark, TINY), str(tmp_path))
    assert state.fits(QS)
    assert not state.fits([CountQuery.build("c", ["events"], (), [("events.value", compare(">=", 51.0))])])


def test_late_rows_drop_behind_the_watermark(spark, tmp_path):
    src = str(tmp_path / "src")
    at = lambda d, h: datetime(2024, 1, d, h)
    write = lambda rows: spark.createDataFrame(rows, "event_id bigint, ts timestamp, event_type string, value double").coalesce(1).write.mode("append").parquet(src)
    schema = "event_id bigint, ts timestamp, event_type string, value double"
    stream = lambda: spark.readStream.schema(schema).parquet(src).withWatermark("ts", "1 hour")

    def run():
        w = S.windowed_counts(stream(), QS[:1], F.window("ts", "1 day"))
        q = w.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "chk")).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()

    write([(1, at(1, 5), "click", 1.0), (2, at(3, 5), "click", 1.0)])
    run()
    write([(3, at(1, 6), "click", 1.0), (4, at(5, 1), "click", 1.0)])
    run()
    got = {r["window_start"].day: r["n"] for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert got == {1: 1, 3: 1}


def test_dedup_within_watermark(spark, tmp_path):
    src = str(tmp_path / "src")
    rows = [(1, datetime(2024, 1, 1, 1)), (1, datetime(2024, 1, 1, 2)), (2, datetime(2024, 1, 1, 3))]
    spark.createDataFrame(rows, "event_id bigint, ts timestamp").write.parquet(src)
    s = S.dedup(spark.readStream.schema("event_id bigint, ts timestamp").parquet(src), "event_id", "ts", "1 day")
    q = s.writeStream.format("memory").queryName("deduped").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("deduped").count() == 2
