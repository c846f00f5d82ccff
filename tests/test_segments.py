"""Segments: compactions, tables of boundary states, open borders, plans; against enumeration and the serial counter."""

import random

import pytest
from pyspark.sql import functions as F

from episode_engine.functions.model import Episode
from episode_engine.operators import compaction, counting, measures, scheduling, segments, serial, stitching, tracking
from episode_engine.plans import planner
from episode_engine.sources import streams as S

EPS = [Episode.parse("A -(2,9]-> B -(0,12]-> C", "x"), Episode.parse("B -(0,5]-> B", "y"), Episode.parse("C", "z")]


def stream(spark, seed=3, n=60, end=120, keys="pqrs", merge=True):
    rng = random.Random(seed)
    rows = [(k, rng.choice("ABC"), rng.randint(0, end), 1) for k in keys for _ in range(n)]
    return spark.createDataFrame(sorted(set(rows)) if merge else rows, "stream_key string, event_type string, t long, mult long")


def counts(df):
    return {(r.episode_id, r.stream_key): r.n for r in df.collect()}


def paths(ev):
    return sorted((r.stream_key, r.t_start, r.t_end) for r in tracking.track_forward_all(ev, EPS[:1]).collect())


def test_same_instants_keep_one_row_for_each_path(spark):
    """A0 B1 B2 C5: two paths from 0 to 5."""
    ev = spark.createDataFrame([("s", "A", 0, 1), ("s", "B", 1, 1), ("s", "B", 2, 1), ("s", "C", 5, 1)], "stream_key string, event_type string, t long, mult long")
    e = Episode.parse("A -(0,3]-> B -(0,5]-> C")
    for way in ("unordered", "padded", "count_scan_write"):
        got = [(r.t_start, r.t_end, r["index"]) for r in compaction.track_by(ev, e, way).collect()]
        assert sorted(got) == [(0, 5, 0), (0, 5, 1)], way


@pytest.mark.parametrize("way", ["unordered", "padded", "count_scan_write", "backward"])
def test_compactions_are_dense_and_whole(spark, way):
    ev = stream(spark)
    found = compaction.track_by(ev, EPS[0], way.replace("backward", "count_scan_write"), seg_len=45, backward=way == "backward")
    assert sorted((r.stream_key, r.t_start, r.t_end) for r in found.collect()) == paths(ev)
    if way == "backward":
        got = sorted(compaction.dense(found).collect(), key=lambda r: r["index"])
        assert [r["index"] for r in got] == list(range(len(got)))
        assert all(a.stream_key < b.stream_key or a.t_end <= b.t_end for a, b in zip(got, got[1:], strict=False))


def test_padded_slots_that_overflow_are_an_error(spark):
    with pytest.raises(Exception, match="capacity exceeded"):
        compaction.track_by(stream(spark), EPS[0], "padded", capacity=1).collect()


def test_scan_with_ties_and_an_empty_table(spark):
    rows = [(i, random.Random(i).randint(-5, 5)) for i in range(50)]
    df = spark.createDataFrame(rows, "id long, v long")
    for op, f, zero in (("sum", sum, 0), ("min", min, None), ("max", max, None)):
        got = {r.id: r.scan for r in compaction.exclusive_scan(df, ["id"], "v", op, 7).collect()}
        assert got == {i: f([v for _, v in rows[:i]]) if i else zero for i, _ in rows}
    assert compaction.exclusive_scan(df.limit(0), ["id"], "v").count() == 0


def test_ways_in_segments_equal_full_tracking(spark):
    ev = stream(spark)
    want, n = paths(ev), counts(serial.count_serial(ev, EPS))
    for way in segments.WAYS:
        rows = [r for r in segments.track_compacted(ev, EPS, 45, way, 2).collect() if r.episode_id == "x"]
        assert sorted((r.stream_key, r.t_start, r.t_end) for r in rows) == want, way
        by = {}
        for r in sorted(rows, key=lambda r: (r.stream_key, r.seg, r["index"])):
            by.setdefault((r.stream_key, r.seg), []).append(r.t_end)
        assert all(x == sorted(x) for x in by.values()), way
    got = segments.count_compacted(ev, EPS, 45).collect()
    assert {(r.way, r.episode_id, r.stream_key): r.n for r in got} == {(w, *k): v for w in segments.WAYS for k, v in n.items()}
    assert {r.paths for r in got if r.episode_id == "x" and r.stream_key == "p"} == {sum(k == "p" for k, _, _ in want)}


@pytest.mark.parametrize("seed", range(6))
def test_machines_and_tables_on_sparse_and_dense_streams(spark, seed):
    rng = random.Random(seed)
    ev = stream(spark, seed, n=rng.choice([8, 40, 90]), end=rng.choice([60, 300]), merge=False)
    want = counts(serial.count_serial(ev, EPS))
    for length in (5, 23, 80):
        assert counts(counting.count_nonoverlapping(ev, EPS, seg_len=length)) == want, length
        assert counts(stitching.count_segment_machines(ev, EPS, length)) == want, length
    assert counts(counting.count_nonoverlapping(ev, EPS)) == want
    assert counts(counting.count_nonoverlapping(ev, EPS, tracking="union", seg_len=31)) == want


def test_open_borders_are_few_and_counted(spark):
    ev = stream(spark, 3)
    fell = {length: sum(r.by_tables for r in stitching.machine_counts(ev, EPS, length).collect()) for length in (9, 30, 60)}
    assert fell[9] >= 1 and fell[60] == 0


def test_times_far_beyond_doubles(spark):
    base = 2**60 + 7
    rows = [("s", ty, base + t, 1) for ty, t in (("A", 0), ("B", 4), ("C", 9), ("A", 20), ("B", 25), ("C", 30))]
    ev = spark.createDataFrame(rows, "stream_key string, event_type string, t long, mult long")
    assert [r.n for r in counting.count_nonoverlapping(ev, EPS[:1], seg_len=21).collect()] == [2]
    assert [r.n for r in stitching.count_segment_machines(ev, EPS[:1], 25).collect()] == [2]


def test_position_index_in_two_levels(spark):
    ev = stream(spark)
    rows = lambda df: sorted(map(tuple, df.select("stream_key", "event_type", "t", "pos").collect()))
    assert rows(S.position_index(ev, 17)) == rows(S.position_index(ev))


def test_at_most_so_many_next_events(spark):
    ev = stream(spark)
    every, one = (tracking.track_forward_all(ev, EPS[:1], max_matches=m).count() for m in (None, 1))
    assert one < every and one == tracking.track_forward_all(ev, EPS[:1], max_matches=1, with_path=True).count()


def test_level_sizes_and_divergence_of_nothing(spark):
    ev = spark.createDataFrame([("s", "A", 1, 1)], "stream_key string, event_type string, t long, mult long")
    assert [(r.seeds, r.tests, r.matches) for r in measures.level_sizes(ev, EPS[0]).collect()] == [(1, 0, 0), (0, 0, 0)]


def test_plans_of_the_flagship(spark):
    """No shuffle into one partition, no product, two levels of tables after one shuffle of events."""
    df = counting.count_nonoverlapping(stream(spark, merge=False), EPS, seg_len=45)
    steps, text = planner.plan_steps(df), planner.explain(planner.plan_count(3, 3, 21, 120, 240, 4), df)
    assert "SinglePartition" not in text and "CartesianProduct" not in text and "BroadcastNestedLoop" not in text
    assert steps["shuffles"] <= 5 and steps["python"] == 3 and "utilisation" in text


def test_type_filter_reaches_the_scan(spark):
    from episode_engine import catalog

    plan = catalog.QUERIES["scan_pushdown"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "In(event_type" in plan and "props" not in plan
    plan = catalog.QUERIES["scan_time_range"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(ts" in plan


def test_schedules_agree_on_repeated_ends(spark):
    rows = [("e", "s", a, b) for a, b in ((0, 5), (3, 5), (6, 9), (5, 9), (6, 9), (9, 9), (10, 30), (12, 14))]
    occ = spark.createDataFrame(rows, "episode_id string, stream_key string, t_start long, t_end long").withColumn("seg", F.lit(0).cast("long"))
    want = scheduling.schedule_fold(occ).first().n
    assert all(f(occ).first().n == want for f in (scheduling.schedule_kernel, scheduling.schedule_islands, lambda o: scheduling.schedule_segments(o, 4)))


def test_chosen_of_segments_are_those_of_the_whole_stream(spark):
    occ = tracking.track_window_asof(stream(spark, 5, n=80), EPS)
    rows = lambda df: sorted((r.episode_id, r.stream_key, r.t_start, r.t_end) for r in df.collect())
    want = rows(scheduling.schedule_select(occ))
    assert want and all(rows(scheduling.schedule_select(occ, length)) == want for length in (4, 33, 500))


def test_jumps_cross_segments(spark):
    """Successor pointers from windows of segments equal those of a whole stream, and the fold."""
    rng = random.Random(8)
    occ = spark.createDataFrame([("e", k, s, s + rng.randint(1, 30)) for k in "ab" for s in rng.sample(range(400), 150)] + [("e", "c", 3, 900), ("e", "c", 901, 905)], "episode_id string, stream_key string, t_start long, t_end long")
    want = counts(scheduling.schedule_fold(scheduling.by_end(occ)))
    assert counts(scheduling.schedule_jump(occ)) == want
    for seg_len in (7, 20, 45):
        assert counts(scheduling.schedule_jump(occ, seg_len)) == want
