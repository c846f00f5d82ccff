"""Other frequencies, and logical costs. The costs stand for hardware counters; they are none."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.model import Episode, span
from ..plans.planner import default_segment
from ..sources.streams import segment
from .compaction import compact_unordered, level, seeds
from .scheduling import GROUP
from .segments import level_costs, rounds_run
from .serial import Machine, instants
from .tracking import track_forward_all, track_forward_pruned, track_window_asof


def count_overlapped(ev: DataFrame, episodes: list[Episode]) -> DataFrame:
    """All occurrences, overlapping or not: what run time follows."""
    return track_forward_pruned(ev, episodes).groupBy("episode_id").agg(F.sum("paths").cast("long").alias("paths"), F.count("*").alias("ends"))


def frequency_intervals(ev: DataFrame, episodes: list[Episode]) -> DataFrame:
    return track_forward_all(ev, episodes).select(*GROUP, "t_start", "t_end").distinct().groupBy("episode_id").agg(F.count("*").alias("n"))


def frequency_windows(ev: DataFrame, episodes: list[Episode], width: int) -> DataFrame:
    """How many windows [w, w + width) hold an occurrence: the united length of the window starts that do."""
    occ = track_window_asof(ev, episodes).filter(F.col("t_end") - F.col("t_start") < width)
    r = occ.select(*GROUP, (F.col("t_end") - width + 1).alias("a"), F.col("t_start").alias("b"))
    before = F.max("b").over(W.partitionBy(*GROUP).orderBy("a", "b").rowsBetween(W.unboundedPreceding, -1))
    new = F.greatest(F.lit(0).cast("long"), F.col("b") - F.greatest(F.col("a"), F.coalesce(before + 1, F.col("a"))) + 1)
    return r.withColumn("new", new).groupBy(*GROUP).agg(F.sum("new").alias("n"))


def level_sizes(ev: DataFrame, episode: Episode) -> DataFrame:
    """For each level of tracking all matches: producers, `tests` (pairs that meet in a bucket, each a test of the gap), matches, and the longest list.

    Every path is a producer of its own.
    """
    out, cur = None, seeds(ev, episode)
    for i in range(1, len(episode)):
        met = level(cur, ev, episode, i, tested=True)
        per = met.groupBy("episode_id", "stream_key", "seg", "index").agg(F.count("*").alias("tests"), F.count_if("met").alias("found"))
        b = per.agg(F.coalesce(F.sum("tests"), F.lit(0)).alias("tests"), F.coalesce(F.sum("found"), F.lit(0)).alias("matches"), F.coalesce(F.max("found"), F.lit(0)).alias("longest"))
        row = cur.agg(F.count("*").alias("seeds")).crossJoin(b).select(F.lit(i).cast("long").alias("level"), "seeds", "tests", "matches", "longest")  # single rows
        out = row if out is None else out.unionByName(row)
        cur = compact_unordered(met.filter("met"))
    return out


def divergence(ev: DataFrame, episode: Episode, width: int = 32) -> DataFrame:
    """Groups of `width` seeds in order of time, how many have unequal match counts, and the skew: the largest count by the mean one."""
    cur = seeds(ev, episode)
    counts = cur.join(level(cur, ev, episode, 1).groupBy("stream_key", "t_start").agg(F.count("*").alias("m")), ["stream_key", "t_start"], "left")
    groups = counts.select("stream_key", F.expr(f"index div {width}").alias("g"), F.coalesce("m", F.lit(0)).alias("m")).groupBy("stream_key", "g").agg((F.min("m") != F.max("m")).alias("differs"), F.max("m").alias("most"), F.sum("m").alias("all"), F.count("*").alias("of"))
    skew = F.round(F.max("most") * F.sum("of") / F.sum("all"), 6)
    return groups.agg(F.count("*").alias("groups"), F.coalesce(F.sum(F.col("differs").cast("long")), F.lit(0)).alias("divergent"), skew.alias("skew"))


def launches(nodes: int) -> list[tuple[str, int]]:
    """Global steps of each way: tracking rounds, three calls a round for count-scan-write and for padded slots."""
    rounds = nodes - 1
    return [("unordered", rounds + 1), ("padded", 3 * rounds), ("count_scan_write", 3 * rounds)]


def launches_run(ev: DataFrame, episodes: list[Episode]) -> DataFrame:
    """nodes, way, steps: `launches` of the rounds that tracking these episodes takes, one for each number of nodes, counted on the stream."""
    ran = rounds_run(ev, episodes, default_segment(ev, span(episodes))).groupBy("episode_id").agg(F.max("rounds").alias("rounds"))
    rounds = {r["episode_id"]: r["rounds"] for r in ran.collect()}
    rows = [(len(e), way, steps) for e in episodes for way, steps in launches(rounds.get(e.episode_id, 0) + 1)]
    return ev.sparkSession.createDataFrame(rows, "nodes long, way string, steps long")


def machine_tests(ev: DataFrame, episode: Episode, seg_len: int) -> DataFrame:
    """Tests of the gap that segment machines make, and events that they read: one row for each segment and machine is counted, none is estimated."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        left, right, before, rows = int(pdf["seg"].iat[0]) * seg_len, (int(pdf["seg"].iat[0]) + 1) * seg_len, 0, []
        seen = instants(pdf["t"].tolist(), pdf["event_type"].tolist())
        for j in range(len(episode)):
            m, read = Machine(episode, True), 0
            for t, types in seen:
                if t > left - before - 1:
                    read += 1
                    if m.feed(t, types) and t >= right:
                        break
            rows.append((j, read, m.tests))
            before += episode.high[j] if j < len(episode.high) else 0
        return pd.DataFrame(rows, columns=["machine", "read", "tests"])

    own = ev.filter(F.col("event_type").isin(*set(episode.types))).select("stream_key", "event_type", "t")
    rows = segment(own, seg_len, episode.span, 2 * episode.span).groupBy("stream_key", "seg").applyInPandas(lambda pdf: run(pdf), "machine int, read long, tests long")
    return rows.agg(F.count("*").alias("machines"), F.sum("read").alias("read"), F.sum("tests").alias("tests"))


def profile(ev: DataFrame, episode: Episode, seg_len: int) -> DataFrame:
    """Logical stand-ins for a hardware profile, counted while segment machines and each way of compaction run.

    way, instructions (events read, tests, rows sorted, rows written and slots scanned), branches (tests of the gap), groups and
    divergent groups of LANES producers (null for the machines, which run one by one).
    """
    ways = level_costs(ev, [episode], seg_len).groupBy("way").agg(
        F.sum(F.expr("producers + tests + slots + sorted + matches")).alias("instructions"), F.sum("tests").alias("branches"), F.sum("groups").alias("groups"), F.sum("divergent").alias("divergent")
    )
    none = F.lit(None).cast("long")
    machines = machine_tests(ev, episode, seg_len).select(F.lit("segment_machines").alias("way"), F.expr("read + tests").alias("instructions"), F.col("tests").alias("branches"), none.alias("groups"), none.alias("divergent"))
    return machines.unionByName(ways)
