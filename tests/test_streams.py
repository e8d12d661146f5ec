"""Streams over several batches: late rows, timeouts, restart from a checkpoint, output modes."""

import datetime

import pytest
from pyspark.sql import functions as F

from pairlab.streaming import workloads as S

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def at(minute):
    return datetime.datetime(2024, 1, 1) + datetime.timedelta(minutes=minute)


def write(spark, path, number, rows):
    """One file for one batch; files go in order of time."""
    import time

    full = [(i, at(m), u, k, 1.0, "{}") for i, m, u, k in rows]
    spark.createDataFrame(full, SCHEMA).coalesce(1).write.mode("overwrite").parquet(f"{path}/tmp{number}")
    import glob
    import os
    import shutil

    shutil.copy(glob.glob(f"{path}/tmp{number}/part-*.parquet")[0], f"{path}/events{number}.parquet")
    os.utime(f"{path}/events{number}.parquet", (time.time() + number, time.time() + number))


def test_late_rows_are_counted(spark, tmp_path):
    write(spark, tmp_path, 1, [(1, 0, 1, "view"), (2, 30, 1, "view"), (3, 200, 1, "view")])
    write(spark, tmp_path, 2, [(4, 5, 1, "view"), (5, 210, 1, "view")])  # held against the watermark before the first batch, so it counts
    write(spark, tmp_path, 3, [(6, 6, 1, "view"), (7, 500, 1, "view")])  # far behind the watermark of the first
    out = S.drain(S.stream(spark, str(tmp_path), 1).groupBy(F.window("time", "1 hour")).agg(F.count("*").alias("n")), "late")
    got = {r.window.start.hour: (r.n, r.n_late) for r in S.with_late_rows(out).collect()}
    assert got[0] == (3, 1) and out.late_rows == 1


def test_replay_without_late_rows_equals_the_batch(spark, tmp_path):
    rows = [(i, 7 * i, i % 3, "purchase" if i % 4 == 0 else "view") for i in range(60)]
    for k in range(4):
        write(spark, tmp_path, k, rows[15 * k : 15 * k + 15][:: (-1) ** k])
    out = S.drain(S.group_advantages(S.stream(spark, str(tmp_path), 1), None), "adv")
    assert out.late_rows == 0
    want = {}
    for u in range(3):
        mine = [r for r in rows if r[2] == u]
        for g in range(len(mine) // 8):
            reward = [1.0 if r[3] == "purchase" else -1.0 for r in mine[8 * g : 8 * g + 8]]
            m = sum(reward) / 8
            sd = (sum((x - m) ** 2 for x in reward) / 8) ** 0.5
            for r, x in zip(mine[8 * g :], reward):
                want[r[0]] = (u, g, 0.0 if sd == 0 else (x - m) / sd)
    got = {r.event_id: (r.query_id, r.iteration, r.advantage) for r in out.collect()}
    assert set(got) == set(want) and all(got[k][:2] == want[k][:2] and got[k][2] == pytest.approx(want[k][2], abs=1e-6) for k in got)


def test_a_group_that_waits_too_long_is_incomplete(spark, tmp_path):
    write(spark, tmp_path, 1, [(i, i, 1, "purchase" if i == 2 else "view") for i in range(3)])
    write(spark, tmp_path, 2, [(100 + i, 600 + i, 2, "view") for i in range(8)])
    write(spark, tmp_path, 3, [(200, 900, 3, "view")])
    out = S.drain(S.group_advantages(S.stream(spark, str(tmp_path), 1), "3600000"), "waits").collect()
    one = sorted((r.event_id, r.iteration, r.incomplete) for r in out if r.query_id == 1)
    assert one == [(0, 0, True), (1, 0, True), (2, 0, True)]
    assert all(not r.incomplete for r in out if r.query_id == 2 and r.event_id < 108)


def test_a_restart_goes_on_from_the_checkpoint(spark, tmp_path):
    from pairlab.sources.tables import shared_path

    src = tmp_path / "in"
    src.mkdir()
    path = shared_path(spark, "restart")
    write(spark, src, 1, [(i, i, 1, "view" if i else "purchase") for i in range(5)])
    first = S.drain(S.group_advantages(S.stream(spark, str(src), 1), None), "restart", path=path)
    assert first.count() == 0  # five of eight
    write(spark, src, 2, [(i, i, 1, "view") for i in range(5, 12)])
    second = S.drain(S.group_advantages(S.stream(spark, str(src), 1), None), "restart", path=path)
    assert sorted(r.event_id for r in second.collect()) == list(range(8))


@pytest.mark.parametrize("mode", ["update", "complete"])
def test_output_modes_agree_on_totals(spark, tmp_path, mode):
    for k in range(3):
        write(spark, tmp_path, k, [(10 * k + i, 60 * k + i, 1, "view") for i in range(5)])
    out = S.drain(S.stream(spark, str(tmp_path), 1).groupBy(F.window("time", "1 hour")).agg(F.count("*").alias("n")), mode, mode)
    got = {r.h: r.n for r in out.groupBy(F.hour("window.start").alias("h")).agg(F.max("n").alias("n")).collect()}
    assert got == {0: 5, 1: 5, 2: 5}
