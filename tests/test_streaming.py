import os

import pandas as pd

from evenbatch.plans.packing import pack_greedy, pack_local
from evenbatch.relational import session_window_sizes, stream_tumbling_load
from evenbatch.streaming import streams


def parts(spark, sf, tmp_path, n=4):
    events = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts").toPandas()
    events["ts"] = events["ts"].astype("datetime64[us]")
    size = -(-len(events) // n)
    for i in range(n):
        events.iloc[i * size : (i + 1) * size].to_parquet(tmp_path / f"part-{i:02d}.parquet", index=False)
    return str(tmp_path)


def run(df, mode="complete"):
    q = df.writeStream.format("memory").queryName("out").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table("out").collect()


def test_windows_and_sessions_equal_their_batch_twins(spark, sf, tmp_path):
    path = parts(spark, sf, tmp_path)
    live = streams.with_lateness(streams.stream_events(spark, path), "3650 days")
    assert sorted(map(tuple, run(streams.stream_window_load(live, "12 hours")))) == sorted(map(tuple, stream_tumbling_load(spark, sf).collect()))
    assert sorted(map(tuple, run(streams.stream_sessions(live)))) == sorted(map(tuple, session_window_sizes(spark, sf).collect()))


def test_duplicates_go_and_rows_are_enriched(spark, sf, tmp_path):
    path = parts(spark, sf, tmp_path)
    live = streams.with_lateness(streams.stream_events(spark, path), "3650 days")
    names = spark.createDataFrame([(u, f"u{u}") for u in range(100)], "user_id long, name string")
    got = run(streams.stream_enrich(streams.stream_dedup(live, ["user_id"]), names, "user_id").select("user_id", "name"), "append")
    assert len(got) == len({r.user_id for r in got}) and all(r.name == f"u{r.user_id}" for r in got if r.user_id < 100)


def items(tmp_path, n=3):
    frame = pd.DataFrame({"id": range(60), "key": [i % 3 for i in range(60)], "size": [(i * 7) % 11 + 1 for i in range(60)]})
    for i in range(n):
        frame.iloc[i * 20 : (i + 1) * 20].to_parquet(tmp_path / f"items-{i}.parquet", index=False)
    return frame


def test_micro_batches_are_packed(spark, tmp_path):
    src, out = tmp_path / "src", tmp_path / "out"
    src.mkdir()
    frame = items(src)
    live = spark.readStream.schema("id long, key long, size long").option("maxFilesPerTrigger", 1).parquet(str(src))
    streams.stream_pack(live, 20, 2, str(out), str(tmp_path / "ck")).awaitTermination()
    got = spark.read.parquet(str(out)).collect()
    assert len(got) == 60
    for b in {r.batch for r in got}:
        rows = sorted((r for r in got if r.batch == b), key=lambda r: r.id)
        assert [r.bin_id for r in rows] == pack_local([r.size for r in rows], 20, 2)[0]
    assert sorted(r.id for r in got) == frame["id"].tolist()


def test_open_bins_are_carried(spark, tmp_path):
    src = tmp_path / "src"
    src.mkdir()
    frame = items(src)
    live = spark.readStream.schema("id long, key long, size long").option("maxFilesPerTrigger", 1).parquet(str(src))
    got = run(streams.stream_next_fit(live, "key", 20), "append")
    for key, part in frame.groupby("key"):
        loads = {}
        for r in got:
            if r.key == key:
                loads[r.bin_id] = loads.get(r.bin_id, 0) + r.size
        assert max(loads.values()) <= 20 and len(loads) <= max(pack_greedy(part["size"].tolist(), 20, "next")) + 3


def late_rows(tmp_path):
    """Four files, an hour a row; the last brings a row of the first hours, long behind the watermark. Rows are late by
    the watermark of the batch before theirs, so one file lies between."""
    hours = [[0, 1, 2], [30, 31, 32], [40], [60, 1, 61]]
    for i, part in enumerate(hours):
        ts = pd.to_datetime(["2024-01-01"] * len(part)) + pd.to_timedelta(part, unit="h")
        pd.DataFrame({"event_id": [10 * i + k for k in range(len(part))], "ts": ts.astype("datetime64[us]"), "user_id": 1, "event_type": "x", "value": 1.0, "props": ""}).to_parquet(tmp_path / f"late-{i}.parquet", index=False)
        os.utime(tmp_path / f"late-{i}.parquet", (1_700_000_000 + i, 1_700_000_000 + i))  # files come in the order of their times
    return str(tmp_path)


def test_a_late_row_is_left_out_by_the_watermark_and_kept_without_one(spark, tmp_path):
    path = late_rows(tmp_path)
    short = streams.with_lateness(streams.stream_events(spark, path), "2 hours")
    got = run(streams.stream_window_load(short, "12 hours"), "append")
    day = 12 * 3600 * 1_000_000
    first = min(r.start for r in got)
    assert {(r.start - first) // day: r.events for r in got}[0] == 3  # the late row would make four
    long = streams.with_lateness(streams.stream_events(spark, path), "365 days")
    assert min((r.start, r.events) for r in run(streams.stream_window_load(long, "12 hours")))[1] == 4


def test_output_modes_agree_on_the_last_state(spark, tmp_path):
    path = late_rows(tmp_path)
    live = lambda: streams.stream_window_load(streams.with_lateness(streams.stream_events(spark, path), "365 days"), "12 hours")
    whole = {r.start: r.events for r in run(live(), "complete")}
    last = {}
    for r in run(live(), "update"):
        last[r.start] = max(r.events, last.get(r.start, 0))
    assert last == whole


def test_a_stopped_stream_goes_on_where_it_was(spark, tmp_path):
    src, out, ck = tmp_path / "src", tmp_path / "out", tmp_path / "ck"
    src.mkdir()
    frame = items(src, 3)
    (src / "items-2.parquet").rename(tmp_path / "held.parquet")
    live = lambda: spark.readStream.schema("id long, key long, size long").option("maxFilesPerTrigger", 1).parquet(str(src))
    streams.stream_pack(live(), 20, 2, str(out), str(ck)).awaitTermination()
    assert spark.read.parquet(str(out)).count() == 40
    (tmp_path / "held.parquet").rename(src / "items-2.parquet")
    streams.stream_pack(live(), 20, 2, str(out), str(ck)).awaitTermination()
    got = spark.read.parquet(str(out)).collect()
    assert sorted(r.id for r in got) == frame["id"].tolist() and len({r.batch for r in got}) == 3
