"""Streams replayed from files: order, restart, late events, bounded state."""

import random

from pyspark.sql import functions as F

from episode_engine.functions.model import Episode
from episode_engine.operators.serial import Machine, count_instants, instants
from episode_engine.streaming import online

SECOND = 1_000_000
EPISODES = [Episode.of("A", "B", gaps=[(0, 8 * SECOND)]), Episode.of("A", "B", "A", gaps=[(SECOND, 9 * SECOND)] * 2)]


def replayed(spark, place, files_per_batch=1):
    rows = spark.readStream.schema("stream_key string, event_type string, t long").option("maxFilesPerTrigger", files_per_batch).json(f"{place}/in")
    return rows.withColumn("event_time", F.timestamp_micros("t"))


def put(spark, place, n, rows):
    spark.createDataFrame(rows, "stream_key string, event_type string, t long").coalesce(1).write.mode("append").json(f"{place}/in")


def expected(rows):
    return {(e.episode_id, k): count_instants(e, instants([t for s, _, t in rows if s == k], [ty for s, ty, _ in rows if s == k])) for e in EPISODES for k in ("x", "y")}


def latest(df):
    return {(r.episode_id, r.stream_key): r.n for r in df.groupBy("episode_id", "stream_key").agg(F.max("n").alias("n")).collect()}


def test_shuffled_replay_and_restart(spark, tmp_path):
    rng = random.Random(4)
    rows = [(rng.choice("xy"), rng.choice("ABC"), (1000 + i) * SECOND) for i in range(240)]
    late_by = sorted(rows, key=lambda r: r[2] + rng.randint(0, 20) * SECOND)  # out of order by 20 s at most
    place = str(tmp_path)
    for i in range(0, 120, 40):
        put(spark, place, i, late_by[i : i + 40])
    run = lambda: online.run_available(online.online_count(replayed(spark, place), EPISODES, "30 seconds"), "update", f"{place}/run")
    run()
    for i in range(120, 240, 40):
        put(spark, place, i, late_by[i : i + 40])
    got = run()  # goes on from the checkpoint
    assert latest(got) == expected(rows)
    assert got.agg(F.max("late")).first()[0] == 0
    assert got.agg(F.max("settled")).first()[0] > 0
    assert got.agg(F.max("held")).first()[0] < 120


def test_events_behind_the_watermark_do_not_count(spark, tmp_path):
    place = str(tmp_path)
    first = [("x", "A", 1000 * SECOND), ("x", "B", 1005 * SECOND), ("x", "C", 2000 * SECOND), ("x", "A", 2000 * SECOND)]
    run = lambda: online.run_available(online.online_count(replayed(spark, place), EPISODES[:1], "10 seconds"), "update", f"{place}/run")
    put(spark, place, 0, first)
    run()
    put(spark, place, 1, [("x", "A", 1010 * SECOND), ("x", "B", 1012 * SECOND), ("x", "B", 2003 * SECOND)])
    assert latest(run()) == {("A>B", "x"): 2}


def test_state_stays_within_reach():
    m = Machine(EPISODES[1], evict=True)
    for i in range(5000):
        m.feed(i * SECOND, {"A"} if i % 3 else {"C"})
        assert sum(len(x) for x in m.lists[1:]) <= 10
    online.feed(m, [[10_000 * SECOND, "B"]])
    assert m.n == 0


def test_nothing_in_nothing_out(spark, tmp_path):
    put(spark, str(tmp_path), 0, [("x", "C", 5)])
    assert online.run_available(online.online_count(replayed(spark, str(tmp_path)), EPISODES, "1 second"), "update").count() == 0


def test_interval_join_meets_neighbours_only(spark, tmp_path):
    """Equal to all pairs, repeats and bucket borders included, and dealt by time: one key for a whole stream compares all with all."""
    rng = random.Random(9)
    rows = [("x", rng.choice("ABC"), (2016 + rng.randint(0, 400)) * SECOND // 2) for _ in range(300)] + [("y", "A", 1008 * SECOND), ("y", "B", 1017 * SECOND), ("y", "B", 1017 * SECOND), ("y", "B", 1017 * SECOND + 1), ("y", "B", 1010 * SECOND)]
    put(spark, str(tmp_path), 0, rows)
    joined = online.interval_join(replayed(spark, str(tmp_path)), replayed(spark, str(tmp_path)), "A", "B", 2 * SECOND, 9 * SECOND, "10 minutes")
    keys = joined._jdf.queryExecution().analyzed().toString().split("Join Inner, ")[1].split("\n")[0]
    assert "bucket" in keys and "meets" in keys
    got = sorted((r.stream_key, r.t_start, r.t_end) for r in online.run_available(joined, "append").collect())
    want = sorted((k, a, b) for k, x, a in rows if x == "A" for j, y, b in rows if y == "B" and j == k and 2 * SECOND < b - a <= 9 * SECOND)
    assert got == want and len(want) > 200
