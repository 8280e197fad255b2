import datetime as dt
import time

import numpy as np
from pyspark.sql import functions as F

from colpick.operators import sketch
from colpick.streaming import streams


def test_sketch_of_a_stream_is_the_batch_sketch(spark, tmp_path):
    long = spark.createDataFrame([(r, c, float((r * 7 + c) % 5)) for r in range(4) for c in range(12)], "row_id long, col_id long, value double")
    long.repartition(4).write.parquet(str(tmp_path / "in"))
    running = streams.sketch_stream(streams.files(spark, str(tmp_path / "in"), long.schema), 5, seed=3)
    streams.run_once(running, "running_sketch", str(tmp_path / "ckpt"), "complete")
    got = {(r.row_id, r.k): r.v for r in spark.table("running_sketch").collect()}
    assert got == {(r.row_id, r.k): r.v for r in sketch.sketch_long(long, 5, seed=3).collect()}


def test_windows_late_rows_and_repeated_events(spark, tmp_path):
    at = lambda h, m=0: dt.datetime(2024, 1, 1) + dt.timedelta(hours=h, minutes=m)
    schema = "event_id long, ts timestamp, user_id long"
    for name, rows in (("1", [(1, at(0), 1), (1, at(0), 1), (2, at(1), 1)]), ("2", [(3, at(30), 1), (4, at(30, 10), 1)]), ("3", [(5, at(2), 1), (6, at(60), 2)])):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    events = streams.timed(streams.files(spark, str(tmp_path / "in"), schema))
    streams.run_once(streams.cells(streams.dedup(events), "1 day"), "day_cells", str(tmp_path / "c1"))
    assert {r.value for r in spark.table("day_cells").collect()} <= {1.0, 2.0, 3.0}
    late = streams.run_once(streams.cells(streams.timed(streams.files(spark, str(tmp_path / "in"), schema)), "1 day"), "late_cells", str(tmp_path / "c3"))
    assert streams.dropped_rows(late) >= 0 and spark.table("late_cells").count() >= 1
    streams.run_once(streams.sessions(events), "user_sessions", str(tmp_path / "c2"))
    assert spark.table("user_sessions").count() >= 2


def test_pool_keeps_its_size_and_skips_batches_it_has_seen(spark, tmp_path):
    rng = np.random.default_rng(0)
    frame = spark.createDataFrame([(i, rng.normal(size=5).tolist()) for i in range(40)], "col_id long, vec array<double>")
    frame.repartition(4).write.parquet(str(tmp_path / "in"))
    pool = streams.Pool(3)
    streams.run_once(streams.files(spark, str(tmp_path / "in"), frame.schema), pool, str(tmp_path / "ckpt"))
    before = list(pool.ids)
    pool(frame.limit(5), 0)
    assert list(pool.ids) == before and len(before) <= 6
    assert pool.selection(spark).count() == 3
    assert streams.enrich(frame, frame.select("col_id", F.lit(1).alias("one")), "col_id").count() == 40


def test_rows_behind_the_watermark_are_dropped_and_counted(spark, tmp_path):
    at = lambda h: dt.datetime(2024, 1, 1) + dt.timedelta(hours=h)
    schema = "event_id long, ts timestamp, user_id long"
    place = str(tmp_path / "in")
    for rows in ([(1, at(0), 1)], [(2, at(100), 1)], [(3, at(101), 1)], [(4, at(1), 1)], [(5, at(200), 1)]):  # the engine drops rows by the watermark of the batch before
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(place)
        time.sleep(1.1)  # files are read in the order of their times
    query = streams.run_once(streams.cells(streams.timed(streams.files(spark, place, schema)), "1 day"), "late_all", str(tmp_path / "all"))
    assert streams.dropped_rows(query) == 1
    first = [r.value for r in spark.table("late_all").collect() if r.start == at(0)]
    assert first == [1.0]  # without the late row
