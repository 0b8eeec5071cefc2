"""Streams against their batch twins, late rows, restarts, epochs by batches;
the single-process traffic baseline against the engine."""

from datetime import datetime, timedelta

import numpy as np
import pytest

from tickspace import models
from tickspace.baseline import noise_array, traffic_numpy
from tickspace.functions.exact import noise
from tickspace.operators import runtime
from tickspace.streaming import sightings as st

START = datetime(2024, 1, 1)
SCHEMA = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double"


def rows(df):
    return sorted(map(tuple, df.collect()))


def put(spark, folder, minutes, first=0):
    data = [(first + i, START + timedelta(minutes=m), i % 3, "ab"[i % 2], float(i)) for i, m in enumerate(minutes)]
    spark.createDataFrame(data, SCHEMA).coalesce(1).write.mode("append").parquet(str(folder))


def source(spark, folder):
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(str(folder))


def test_stream_equals_batch_and_goes_on_after_a_restart(spark, tmp_path):
    put(spark, tmp_path / "in", [0, 10, 61, 62, 125])
    first = st.drain(st.tumbling(source(spark, tmp_path / "in")), path=str(tmp_path / "run"))
    assert rows(first) == rows(st.tumbling(spark.read.parquet(str(tmp_path / "in"))))
    put(spark, tmp_path / "in", [130, 200], first=5)
    again = st.drain(st.tumbling(source(spark, tmp_path / "in")), path=str(tmp_path / "run"))
    assert rows(again) == rows(st.tumbling(spark.read.parquet(str(tmp_path / "in"))))


def test_late_rows_are_dropped_in_append_mode(spark, tmp_path):
    folder = tmp_path / "in"
    put(spark, folder, [0, 5])
    run = lambda: st.drain(st.tumbling(source(spark, folder)), "append", str(tmp_path / "run"))
    run()
    put(spark, folder, [600])
    run()
    put(spark, folder, [7, 605])  # the former is far behind the watermark
    run()
    put(spark, folder, [1200])
    assert [n for _, n in rows(run())] == [2, 2]


def test_updates_equal_the_complete_table(spark, tmp_path):
    for i, minutes in enumerate([[0, 10, 61], [2, 62, 125], [126]]):
        put(spark, tmp_path / "in", minutes, first=10 * i)
    got = st.drain(st.tumbling(source(spark, tmp_path / "in"), late="1 day"), "update", str(tmp_path / "run"), ("start",))
    assert got.columns == ["start", "n"]
    assert rows(got) == rows(st.tumbling(spark.read.parquet(str(tmp_path / "in"))))
    with pytest.raises(ValueError):
        st.drain(st.tumbling(source(spark, tmp_path / "in")), "update", str(tmp_path / "other"))


def test_empty_stream(spark, tmp_path):
    put(spark, tmp_path / "in", [])
    assert rows(st.drain(st.tumbling(source(spark, tmp_path / "in")), path=str(tmp_path / "run"))) == []


def test_repeated_rows_count_once(spark, tmp_path):
    put(spark, tmp_path / "in", [0, 1])
    put(spark, tmp_path / "in", [0, 1])
    assert len(rows(st.drain(st.first_seen(source(spark, tmp_path / "in")), "append", str(tmp_path / "run")))) == 2


def test_epochs_by_batches(spark, tmp_path):
    world = models.basic_fish()
    schema = "id bigint, x bigint, y bigint, vx bigint, vy bigint"
    make = lambda lo: spark.createDataFrame([(lo + i, i * 50, i * 30, i % 5, 1) for i in range(12)], schema)
    folder, path = str(tmp_path / "in"), str(tmp_path / "run")
    make(0).coalesce(1).write.parquet(folder)
    stream = lambda: spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)
    assert st.stream_epochs(stream(), "fish", world, path, 2)[1] == 2
    make(100).coalesce(1).write.mode("append").parquet(folder)
    got, at = st.stream_epochs(stream(), "fish", world, path, 2)
    assert at == 4
    plain = runtime.run({"fish": make(0)}, world, 2, path=str(tmp_path / "a")).world["fish"]
    both = plain.unionByName(make(100).select(*plain.columns))
    want = runtime.run({"fish": both}, world, 4, start_tick=2, path=str(tmp_path / "b")).world["fish"]
    assert runtime.same_world(got["fish"], want)


def cars(spark, n):
    return spark.createDataFrame([(i * 3, i * 7 % 5, (i * 41 % 97) * 25, 180 + i % 60, 200 + i % 90) for i in range(n)], "id bigint, lane bigint, pos bigint, v bigint, desired bigint")


@pytest.mark.parametrize("n", [0, 1, 150])
@pytest.mark.parametrize("length", [None, 1500])
def test_traffic_baseline_equals_the_engine(spark, tmp_path, n, length):
    road = cars(spark, n)
    want = runtime.run({"vehicle": road}, models.traffic(length=length), 2, path=str(tmp_path)).world["vehicle"]
    assert rows(traffic_numpy(road, 2, length=length).select("id", "lane", "pos", "v")) == rows(want.select("id", "lane", "pos", "v"))


def test_noise_of_arrays(spark):
    got = [r[0] for r in spark.range(50).selectExpr(noise("id", 4, 9)).collect()]
    assert noise_array(np.arange(50), 4, 9).tolist() == got
