"""Workloads of the catalog that have to be whole: every episode on every step and by every counter, against the serial one."""

import random
from collections import defaultdict

from episode_engine import catalog, workloads
from episode_engine.functions.model import Episode
from episode_engine.operators import serial
from episode_engine.sources import streams as S

SF = "/root/testdata/sf0.001"


def test_every_counter_on_every_step_of_the_ladder(spark):
    unit, ev, want = S.unit(spark, SF), S.events_by_type(spark, SF).cache(), {}
    for a, b in S.LADDER:
        counted = serial.count_serial(S.ladder_prefix(ev, (a, b)), [catalog.gapped(p, 5, 10, unit) for p in catalog.THIRTY])
        want |= {(a, b, r.episode_id): r.n for r in counted.collect()}
    assert len(want) == 240
    got = defaultdict(dict)
    for r in catalog.QUERIES["w1_methods"](spark, SF).collect():
        got[r.method][r.num, r.den, r.episode_id] = r.n
    assert set(got) == set(workloads.COUNTERS) and all(x == want for x in got.values())
    assert {(r.num, r.den, r.episode_id): r.n for r in catalog.QUERIES["w1_ladder"](spark, SF).collect()} == want


def test_planted_chains_are_mined(spark):
    found, chains = workloads.mine_planted(spark, 10)
    assert {tuple(c) for c in chains} <= set(found)


def test_phrases_by_hand(spark):
    got = {r.phrase: (r.documents, r.n) for r in catalog.QUERIES["count_phrases"](spark, SF).collect()}
    phrases = set(S.benchmark_passages(spark, SF, workloads.PHRASE_WORDS))
    want = defaultdict(lambda: [0, 0])
    import re

    for (text,) in S.table(spark, SF, "documents").select("text").collect():
        w = re.split(r"[\W_]+", (text or "").lower())
        for p in phrases:
            n, free = 0, 0
            for i in range(len(w) - len(p) + 1):
                if i >= free and tuple(w[i : i + len(p)]) == p:
                    n, free = n + 1, i + len(p)
            if n:
                want[" ".join(p)][0] += 1
                want[" ".join(p)][1] += n
    assert got == {k: tuple(v) for k, v in want.items()}


def test_machine_profile_counts_tests(spark):
    rows = {r.way: r for r in catalog.QUERIES["w2_machines"](spark, SF).collect()}
    assert rows["count_scan_write"].branches == 2 * rows["unordered"].branches > 0
    assert rows["padded"].instructions > rows["unordered"].instructions
    assert rows["segment_machines"].branches > 0


def test_serial_counter_streams_its_rows(spark):
    """Batches of seven rows, with instants and streams that go on in the next batch; no stream is a group that Python holds whole."""
    rng = random.Random(3)
    rows = [(rng.choice("xyz"), rng.choice("ABC"), rng.randint(0, 150), 1) for _ in range(400)] + [("only", "C", 5, 1)]
    ev = spark.createDataFrame(rows, "stream_key string, event_type string, t long, mult long")
    eps = [Episode.of("A", "B", gaps=[(0, 8)]), Episode.of("A", "A", "B", gaps=[(1, 9), (0, 6)]), Episode.of("B", "C", "B", gaps=[(2, 7)] * 2), Episode.of("C")]
    want = {(e.episode_id, k): serial.count_instants(e, serial.instants([t for j, _, t, _ in rows if j == k], [ty for j, ty, _, _ in rows if j == k])) for e in eps for k in ("x", "y", "z", "only")}
    assert max(want.values()) > 5
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 7)
    try:
        for found in (serial.count_serial(ev, eps), serial.count_serial(ev, eps, evict=True), serial.count_episode_parallel(ev, eps)):
            assert "InPandas" not in found._jdf.queryExecution().executedPlan().toString()
            assert {(r.episode_id, r.stream_key): r.n for r in found.collect()} == want
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def equals_sql(spark, place, names, where="TRUE", copies=2):
    """Queries against their SQL over `events` of the smallest tables, each row `copies` times."""
    import duckdb

    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    con.sql(f"COPY (SELECT event_id + 100000 * i AS event_id, * EXCLUDE (event_id, i) FROM '{SF}/events.parquet', range({copies}) r(i) WHERE {where}) TO '{place}/events.parquet' (FORMAT parquet)")
    con.sql(f"CREATE VIEW events AS FROM '{place}/events.parquet'")
    for name in names:
        want = con.sql(catalog.SQL[name])
        got = catalog.QUERIES[name](spark, str(place)).select(*want.columns)
        assert sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, want.fetchall())), name
    return con


def test_rows_that_fall_together(spark, tmp_path):
    equals_sql(spark, tmp_path, ["stream_events"])


def test_ladder_of_repeats_and_of_a_late_start(spark, tmp_path):
    (tmp_path / "late").mkdir()
    equals_sql(spark, tmp_path, ["dataset_ladder"])
    equals_sql(spark, tmp_path / "late", ["dataset_ladder"], "ts > TIMESTAMP '2024-01-02'", 1)


def test_costs_and_candidates_follow_the_table(spark, tmp_path):
    con = equals_sql(spark, tmp_path, ["cost_launches", "mine_prune"], "event_type <> 'error'", 1)
    assert con.sql(f"SELECT max(steps) FROM ({catalog.SQL['cost_launches']}) WHERE way = 'padded'").fetchall() == [(9,)]  # the fourth type never comes


def test_chains_planted_into_events(spark, tmp_path):
    con = equals_sql(spark, tmp_path, ["w7_generator"], "TRUE", 1)
    starts = con.sql(f"SELECT count(*) FROM events WHERE event_id % {S.CHAIN_EVERY} = 0").fetchall()[0][0]
    assert catalog.QUERIES["w7_generator"](spark, str(tmp_path)).agg({"n": "sum"}).first()[0] > starts // 2
