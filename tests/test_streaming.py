"""Streams against batches."""

import datetime
import time

import pytest

from slidemedian.operators.filters import sliding_median
from slidemedian.plans.store import fresh_path
from slidemedian.streaming import sliding


def rows(spark, n=60):
    start = datetime.datetime(2024, 1, 1)
    data = [(i, start + datetime.timedelta(minutes=30 * i), i % 2, float((i * 37) % 23)) for i in range(n)]
    return spark.createDataFrame(data, "event_id long, ts timestamp, user_id long, value double")


def test_replay_equals_batch(spark):
    df = rows(spark)
    stream = sliding.replay(df, "ts", "event_id", "user_id", 3, "test-replay")
    got = sliding.run_to_end(sliding.stream_sliding_median(stream, "value", 5, "ts", "event_id", "user_id"), "test-replay")
    expected = sliding_median(df, "value", 5, ["ts", "event_id"], "user_id").select("user_id", "event_id", "pos", "med")
    assert sorted(map(tuple, got.where("id >= 0").collect())) == sorted(map(tuple, expected.collect()))


def test_late_rows_inside_the_watermark_count_and_others_do_not(spark):
    df = rows(spark, 40)
    folder = fresh_path(spark, "test-late")
    parts = [df.where("event_id < 20 AND event_id != 19"), df.where("event_id >= 20 OR event_id = 19"), df.where("event_id = 0")]
    for part in parts:
        part.coalesce(1).write.mode("append").parquet(folder)
    sliding.flush_row(df, "ts", "event_id", None).coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    got, late = sliding.run_counted(sliding.stream_sliding_median(stream, "value", 5, "ts", "event_id"), "test-late")
    assert late == 1
    expected = sliding_median(df, "value", 5, ["ts", "event_id"]).select("event_id", "pos", "med")
    assert sorted(tuple(r)[1:] for r in got.where("id >= 0").collect()) == sorted(map(tuple, expected.collect()))


def test_modes_agree(spark):
    df = rows(spark, 90)
    wanted = sorted(map(tuple, sliding_median(df, "value", 31, ["ts", "event_id"]).select("event_id", "pos", "med").collect()))
    for mode in ("blocks", "ordered", "auto"):
        stream = sliding.replay(df, "ts", "event_id", None, 4, f"test-{mode}")
        got = sliding.run_to_end(sliding.stream_sliding_median(stream, "value", 31, "ts", "event_id", mode=mode), f"test-{mode}")
        assert sorted(tuple(r)[1:] for r in got.where("id >= 0").collect()) == wanted
    with pytest.raises(ValueError):
        sliding.stream_sliding_median(stream, "value", 31, "ts", "event_id", mode="fast")


def many(spark, n):
    """Rows a second apart by pairs, which share a time and come in falling order of their ids."""
    made = "id AS event_id", "timestamp_seconds(1704067200 + id div 2) AS ts", "CAST(pmod(hash(id), 5003) AS DOUBLE) AS value"
    return spark.range(n).selectExpr(*made).orderBy("ts", "event_id", ascending=[True, False])


def test_one_state_takes_many_rows(spark):
    """Each trigger leaves 400,000 rows waiting; a state shipped again with every few of them took two minutes."""
    df, held = many(spark, 1_200_000), {name: spark.conf.get(name) for name in sliding.ONE_STATE}
    stream = sliding.replay(df, "ts", "event_id", None, 3, "test-many")
    began = time.monotonic()
    got = sliding.run_to_end(sliding.stream_sliding_median(stream, "value", 25, "ts", "event_id"), "test-many", one_state=True)
    assert time.monotonic() - began < 60
    assert {name: spark.conf.get(name) for name in held} == held
    expected = sliding_median(df, "value", 25, ["ts", "event_id"]).select("event_id", "pos", "med")
    found = got.where("id >= 0").select("id", "pos", "med")
    assert found.count() == expected.count() == 1_200_000 - 24
    assert found.exceptAll(expected).isEmpty()


def test_windows_of_one_state_leave_in_several_tasks(spark, monkeypatch):
    """Neither rows of the result nor their files come from the task that holds the state."""
    monkeypatch.setattr(sliding, "PACK_ROWS", 50)
    df = rows(spark, 2_000)
    stream = sliding.replay(df, "ts", "event_id", None, 2, "test-packed")
    got = sliding.run_to_end(sliding.stream_sliding_median(stream, "value", 5, "ts", "event_id"), "test-packed", one_state=True)
    expected = sliding_median(df, "value", 5, ["ts", "event_id"]).select("event_id", "pos", "med")
    assert sorted(tuple(r)[1:] for r in got.where("id >= 0").collect()) == sorted(map(tuple, expected.collect()))
    counts = [r[0] for r in got.groupBy("_metadata.file_path").count().select("count").collect()]
    assert max(counts) < 900
