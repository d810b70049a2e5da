"""Streams that arrive in turns, late rows, joins of streams, numbering, and raw files in records."""

import uuid
from datetime import datetime, timedelta

import numpy as np
import pytest

from fieldloom.sources import container as box
from fieldloom.streaming import events

START = datetime(2024, 1, 1)
SF = "/root/testdata/sf0.001"


def rows(spark, marks):
    """Events at hours after the start: (id, user, kind, hours, value)."""
    data = [(i, u, kind, START + timedelta(hours=h), float(v)) for i, u, kind, h, v in marks]
    return spark.createDataFrame(data, "event_id bigint, user_id bigint, event_type string, ts timestamp, value double")


def test_late_rows_change_nothing(spark):
    early = rows(spark, [(1, 1, "a", 0, 1), (2, 1, "a", 5, 2), (3, 1, "a", 26, 3)])
    later = rows(spark, [(4, 1, "a", 25, 4), (5, 1, "a", 60, 5)])  # an hour before the last one: in time
    late = rows(spark, [(6, 1, "a", 6, 6), (7, 1, "a", 59.5, 7)])  # the first is of a closed day
    got = {r.day: r.n for r in events.in_turns(spark, [early, later, late], events.tumbling).collect()}
    assert got == {"2024-01-01": 2, "2024-01-02": 2}


def test_updates_give_each_state_of_a_window(spark):
    stream_in = rows(spark, [(1, 1, "a", 0, 1), (2, 1, "a", 30, 2)])
    path = f"{events.shared_folder(spark)}/updates"
    stream_in.write.mode("overwrite").parquet(path)
    got = events.finished(events.tumbling(spark.readStream.schema(stream_in.schema).parquet(path)), "update").collect()
    assert sorted((r.day, r.n) for r in got) == [("2024-01-01", 1), ("2024-01-02", 1)]


def test_streams_meet_in_time(spark):
    both = rows(spark, [(1, 1, "click", 0, 0), (2, 1, "purchase", 6, 0), (3, 1, "purchase", 6.1, 0), (4, 2, "purchase", 1, 0), (5, 1, "click", 6, 0), (6, 1, "purchase", -1, 0)])
    path = f"{events.shared_folder(spark)}/pairs"
    both.write.mode("overwrite").parquet(path)
    got = events.finished(events.followed(spark.readStream.schema(both.schema).parquet(path)), "append").collect()
    assert sorted((r.click, r.purchase) for r in got) == [(1, 2), (5, 2), (5, 3)]


def test_drained_and_rate(spark):
    assert events.first_batch(spark, 50).count() == 50
    both = rows(spark, [(1, 1, "click", 0, 0)])
    path = f"{events.shared_folder(spark)}/drain"
    both.write.mode("overwrite").parquet(path)
    assert events.drained(spark.readStream.schema(both.schema).parquet(path)).exception() is None


def test_numbered(spark):
    ids = np.random.default_rng(2).choice(10 * events.RUN, 500, replace=False) - 3 * events.RUN
    df = spark.createDataFrame([(int(i), "ab"[int(i) % 2]) for i in ids], "event_id bigint, kind string")
    for kind in "ab":
        want = {int(i): n for n, i in enumerate(sorted(x for x in ids if "ab"[int(x) % 2] == kind))}
        assert {r.event_id: r.g for r in events.numbered(df, "kind", "event_id").where(f"kind = '{kind}'").collect()} == want


def test_raw_file_in_records(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(box, "RECORD", 8)
    a = np.random.default_rng(1).normal(size=(3, 4, 5)).astype("<f4")
    path = str(tmp_path / "u.f32")
    (tmp_path / "u.f32").write_bytes(a.tobytes())
    assert box.record_length(60) == 6 and box.record_length(7) == 7 and box.record_length(11) == 1
    got = {(r.i, r.j, r.k): r.value for r in box.raw_field(spark, path, "u", (3, 4, 5)).collect()}
    assert got == {at: float(v) for at, v in np.ndenumerate(a)}
    with pytest.raises(Exception, match="more than 30"):
        box.raw_field(spark, path, "u", (3, 2, 5)).collect()


def test_chain_encoder_is_read_from_files(spark):
    assert events.QUERIES["stream_chain_encoder"](spark, SF).inputFiles()


def test_dedup_is_read_from_files(spark):
    assert events.QUERIES["stream_dedup"](spark, SF).inputFiles()


def test_sessions_are_read_from_the_last_batch(spark):
    path = f"{events.shared_folder(spark)}/{uuid.uuid4().hex}"
    for marks in ([(1, 1, "a", 0, 1), (2, 1, "a", 0.25, 2)], [(3, 1, "a", 0.5, 3), (4, 2, "a", 9, 4)]):
        rows(spark, marks).coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", 1).parquet(path)
    out = events.finished(events.sessions(stream), "complete")
    assert out.inputFiles() and sorted((r.user_id, r.n) for r in out.collect()) == [(1, 3), (2, 1)]
