"""Level-wise discovery of frequent episodes. Frequent sets are small and live on the driver; events never do."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.model import Episode
from ..plans.planner import choose_strategy, default_segment
from ..plans.storage import written
from .counting import count_nonoverlapping
from .serial import count_episode_parallel

SCHEMA = "level int, episode_id string, types array<string>, low array<bigint>, high array<bigint>, n long"


def name(types: tuple, low: tuple, high: tuple) -> str:
    out = types[0]
    for t, a, b in zip(types[1:], low, high, strict=True):
        out += f" ({a},{'inf' if b is None else b}] {t}"
    return out


def frequent_types(ev: DataFrame, theta: int) -> DataFrame:
    counts = ev.groupBy("event_type").agg(F.count_distinct("stream_key", "t").alias("n"))
    return counts.filter(F.col("n") > theta)


def candidates_pairs(types: list[str], gaps: list[tuple[int, int | None]]) -> list[Episode]:
    return [Episode(name((a, b), (lo,), (hi,)), (a, b), (lo,), (hi,)) for a in types for b in types for lo, hi in gaps]


def candidates_join(prev: list[Episode]) -> list[Episode]:
    """Two frequent episodes where the first without its first node is the second without its last, gaps included.

    Only these two parts of a candidate are sure to be as frequent: without a middle node two gaps become one.
    """
    by_head: dict[tuple, list[Episode]] = {}
    for e in prev:
        by_head.setdefault((e.types[:-1], e.low[:-1], e.high[:-1]), []).append(e)
    out = []
    for a in prev:
        for b in by_head.get((a.types[1:], a.low[1:], a.high[1:]), []):
            types, low, high = (*a.types, b.types[-1]), (*a.low, b.low[-1]), (*a.high, b.high[-1])
            out.append(Episode(name(types, low, high), types, low, high))
    return sorted(out, key=lambda e: e.episode_id)


def prune(candidates: list[Episode], frequent: list[Episode]) -> list[Episode]:
    known = {(e.types, e.low, e.high) for e in frequent}
    return [e for e in candidates if (e.types[1:], e.low[1:], e.high[1:]) in known and (e.types[:-1], e.low[:-1], e.high[:-1]) in known]


def totals(counts: DataFrame) -> DataFrame:
    return counts.groupBy("episode_id").agg(F.sum("n").alias("n"))


def mine(ev: DataFrame, gaps: list[tuple[int, int | None]], theta: int, max_level: int = 9, counter: str = "auto") -> list[tuple[int, Episode, int]]:
    """(level, episode, count) of every episode whose count is above theta. One pass over the events for each level.

    Events of frequent types are written once, and the segments of all levels have one length, from the longest episode allowed.
    """
    spark = ev.sparkSession
    rows = [(1, Episode(t, (t,), (), ()), n) for t, n in sorted(map(tuple, frequent_types(ev, theta).collect()))]
    out, level = list(rows), 1
    ev = written(ev.filter(F.col("event_type").isin(*[e.types[0] for _, e, _ in rows])), "events") if rows else ev
    highs = [b for _, b in gaps]
    seg_len = default_segment(ev, max(highs) * (max_level - 1)) if rows and None not in highs and max_level > 1 else None
    size = ev.count()
    while rows and level < max_level:
        level += 1
        own = [e for _, e, _ in rows]
        cand = candidates_pairs([e.types[0] for e in own], gaps) if level == 2 else prune(candidates_join(own), own)
        if not cand:
            break
        how = counter if counter != "auto" else choose_strategy(len(cand), level, size, spark.sparkContext.defaultParallelism)
        counted = count_episode_parallel(ev, cand) if how == "episodes" else count_nonoverlapping(ev, cand, seg_len=seg_len)
        kept = {r[0]: r[1] for r in totals(counted).filter(F.col("n") > theta).collect()}
        rows = [(level, e, kept[e.episode_id]) for e in cand if e.episode_id in kept]
        out += rows
    return out


def as_frame(spark: SparkSession, found: list[tuple[int, Episode, int]]) -> DataFrame:
    return spark.createDataFrame([(lv, e.episode_id, list(e.types), list(e.low), list(e.high), n) for lv, e, n in found], SCHEMA)


def maximal(found: list[tuple[int, Episode, int]]) -> list[tuple[int, Episode, int]]:
    """Those that are neither the first nor the last part of a longer frequent one."""
    covered = set()
    for _, e, _ in found:
        if len(e) > 1:
            covered |= {(e.types[1:], e.low[1:], e.high[1:]), (e.types[:-1], e.low[:-1], e.high[:-1])}
    return [(lv, e, n) for lv, e, n in found if (e.types, e.low, e.high) not in covered]
