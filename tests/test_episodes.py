"""Worked streams, and all counters against the serial one and against enumeration."""

import random
from itertools import product

import pytest

from episode_engine.functions.model import Episode
from episode_engine.operators import counting, scheduling, serial, stitching, tracking
from episode_engine.operators.serial import count_instants, instants

WORKED = [
    ("A1 B4 A10 B16 B18 C20 C27 A30 B36 C50", "A -(5,10]-> B -(10,15]-> C", 2),
    ("A0 A3 B7 B9 C14 A15 C17 B21 B25 C30 A40 B45 C52", "A -(5,10]-> B -(5,10]-> C", 2),
    ("A0 A6 B8", "A -(5,10]-> B", 1),
    ("A0 B5", "A -(5,10]-> B", 0),
    ("A0 B10", "A -(5,10]-> B", 1),
    ("A0 A5 B5 B9", "A -(0,6]-> B", 1),
    ("A0 B1", "A -(0,6]-> B", 1),
    ("A0 A2 A4 A6", "A -(0,3]-> A", 2),
]


def rows(text):
    return [("s", x[0], int(x[1:]), 1) for x in text.split()]


def frame(spark, data):
    return spark.createDataFrame(data, "stream_key string, event_type string, t long, mult long")


def brute(events, e):
    """The largest set of disjoint occurrences, by trying every set of intervals."""
    times = [sorted({t for _, ty, t, _ in events if ty == x}) for x in e.types]
    spans = {(p[0], p[-1]) for p in product(*times) if all(lo < b - a and (hi is None or b - a <= hi) for a, b, lo, hi in zip(p, p[1:], e.low, e.high, strict=False))}

    def best(after):
        return max((1 + best(b) for a, b in spans if a > after), default=0)

    return best(-1)


@pytest.mark.parametrize(("text", "episode", "n"), WORKED)
def test_worked_streams(text, episode, n):
    e, data = Episode.parse(episode), rows(text)
    for evict in (False, True):
        assert count_instants(e, instants([r[2] for r in data], [r[1] for r in data]), evict) == n
    assert brute(data, e) == n


def test_serial_counter_is_optimal():
    rng = random.Random(11)
    for _ in range(300):
        data = [("s", rng.choice("ABC"), rng.randint(0, 20), 1) for _ in range(rng.randint(0, 12))]
        n = rng.randint(1, 3)
        e = Episode.of(*[rng.choice("ABC") for _ in range(n)], gaps=[(lo := rng.randint(0, 4), lo + rng.randint(1, 8)) for _ in range(n - 1)])
        assert count_instants(e, instants([r[2] for r in data], [r[1] for r in data])) == brute(data, e)


def test_all_counters_agree(spark):
    rng = random.Random(3)
    data = sorted({(k, rng.choice("ABC"), rng.randint(0, 120), 1) for k in ("p", "q", "r", "s") for _ in range(60)})
    ev = frame(spark, data)
    eps = [Episode.parse("A -(2,9]-> B -(0,12]-> C", "x"), Episode.parse("B -(0,5]-> B", "y"), Episode.parse("C", "z")]
    get = lambda df: {(r.episode_id, r.stream_key): r.n for r in df.collect()}
    want = get(serial.count_serial(ev, eps))
    for how in counting.TRACKING:
        assert get(counting.count_nonoverlapping(ev, eps, tracking=how, schedule="islands")) == want, how
    for schedule in ("fold", "kernel", "jump"):
        assert get(counting.count_nonoverlapping(ev, eps, schedule=schedule)) == want, schedule
    for length in (7, 45):
        assert get(counting.count_nonoverlapping(ev, eps, seg_len=length, schedule="islands")) == want
        assert get(stitching.count_segment_exact(ev, eps[:2], length)) == {k: v for k, v in want.items() if k[0] != "z"}
    assert get(stitching.count_segment_machines(ev, eps[:1], 60)) == {k: v for k, v in want.items() if k[0] == "x"}
    assert get(serial.count_serial_fold(ev, eps[:1])) == {k: v for k, v in want.items() if k[0] == "x"}
    free = [Episode.of("A", "B", "C")]
    assert get(stitching.count_segment_unconstrained(ev, free, 11)) == get(serial.count_serial_unconstrained(ev, free)) == get(serial.count_serial(ev, free))


def test_chosen_do_not_overlap(spark):
    data = [("s", random.Random(i).choice("AB"), i, 1) for i in range(80)]
    e = [Episode.parse("A -(0,4]-> B")]
    got = sorted((r.t_start, r.t_end) for r in scheduling.schedule_select(tracking.track_window_asof(frame(spark, data), e)).collect())
    assert all(a[1] < b[0] for a, b in zip(got, got[1:], strict=False))


def test_no_events_and_bad_episodes(spark):
    e = [Episode.parse("A -(0,4]-> B")]
    assert [r.n for r in counting.count_nonoverlapping(frame(spark, [("s", "C", 1, 1)]), e).collect()] == [0]
    assert counting.count_nonoverlapping(frame(spark, []), e).count() == 0
    with pytest.raises(ValueError):
        Episode.of("A", "B", gaps=[(5, 5)])


def test_flagship(spark):
    from __spark_entry__ import entry

    assert [r.n for r in entry(spark).collect()] == [33]
