"""Local tracking: a superset of an episode's occurrences, in parallel for every start event.

All forms return episode_id, stream_key, seg, t_start, t_end (and paths where they know it). Each works inside
partitions of (episode, stream, segment); a halo as long as the longest span makes segments independent, and an
occurrence belongs to the segment of its end.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.model import Episode, episode_nodes, expand_roles, gap_ok, span
from ..sources.streams import segment

KEY = ["episode_id", "stream_key", "seg"]
OUT = [*KEY, "t_start", "t_end"]


def roles(ev: DataFrame, episodes: list[Episode], seg_len: int | None = None) -> DataFrame:
    """Events of the episodes' types with the nodes that they can play, and the segments that need them."""
    ev = ev.filter(F.col("event_type").isin(*sorted({t for e in episodes for t in e.types})))
    halo = span(episodes)
    if seg_len is None or halo is None:
        ev = ev.withColumn("seg", F.lit(0).cast("long")).withColumn("is_halo", F.lit(False))
    else:
        ev = segment(ev, seg_len, halo)
    return expand_roles(ev, episodes)


def _owned(rows: DataFrame, n: Column | None = None) -> DataFrame:
    return rows.filter(~F.col("is_halo")).select(*OUT, *[c for c in rows.columns if c in ("paths", "path")])


def _pairs(left: DataFrame, right: DataFrame, episodes: list[Episode], i: int, tested: bool = False) -> DataFrame:
    """left (t_end) meets node i (t) of the episodes where the gap allows: buckets as wide as the bound, two for each left row.

    With `tested` all rows that meet in a bucket are kept, and `met` says which pass the gap. The width is the row's own bound, so that episodes with different gaps meet in one join.
    """
    down = lambda x, y: F.call_function("div", x - F.pmod(x, y), y)
    r = right.withColumn("bucket", F.when(F.col("high").isNull(), F.lit(0).cast("long")).otherwise(down(F.col("t"), F.col("high"))))
    nodes = episode_nodes(left.sparkSession, episodes).filter(F.col("pos") == i)
    bounds = F.broadcast(nodes.select("episode_id", F.col("low").alias("_l"), F.col("high").alias("_h")))
    lo, hi = down(F.col("t_end") + F.col("_l") + 1, F.col("_h")), down(F.col("t_end") + F.col("_h"), F.col("_h"))
    buckets = F.when(F.col("_h").isNull(), F.array(F.lit(0).cast("long"))).otherwise(F.sequence(lo, hi))
    x = left.join(bounds, "episode_id").withColumn("bucket", F.explode(buckets)).drop("_l", "_h", "is_halo", "mult")
    both = x.join(r.drop("event_type", "pos", "n"), [*KEY, "bucket"])
    ok = gap_ok(F.col("t") - F.col("t_end"), F.col("low"), F.col("high"))
    return both.withColumn("met", ok) if tested else both.filter(ok)


def _by_length(found, ev: DataFrame, episodes: list[Episode], seg_len: int | None, **more) -> DataFrame:
    out = None
    for n in sorted({len(e) for e in episodes}):
        part = found(roles(ev, own := [e for e in episodes if len(e) == n], seg_len), n, own, **more)
        out = part if out is None else out.unionByName(part)
    return out


def _forward(rows: DataFrame, n: int, own: list[Episode], pruned: bool, with_path: bool = False, max_matches: int | None = None) -> DataFrame:
    at = lambda i: rows.filter(F.col("pos") == i)
    cur = at(0).select(*KEY, "is_halo", F.col("t").alias("t_start"), F.col("t").alias("t_end"), F.col("mult").cast("decimal(38,0)").alias("paths"), *([F.array("t").alias("path")] if with_path else []))
    for i in range(1, n):
        m = _pairs(cur, at(i), own, i)
        if max_matches:  # the earliest next events of each producer only
            by = W.partitionBy(*KEY, "t_start", "t_end", *(["path"] if with_path else [])).orderBy("t")
            m = m.withColumn("_k", F.dense_rank().over(by)).filter(F.col("_k") <= max_matches).drop("_k")
        if pruned:
            cur = m.groupBy(*KEY, "t").agg(F.max("t_start").alias("t_start"), F.sum(F.col("paths") * F.col("mult")).cast("decimal(38,0)").alias("paths"), F.first("is_halo").alias("is_halo")).withColumnRenamed("t", "t_end")
        else:
            cur = m.select(*KEY, "is_halo", "t_start", F.col("t").alias("t_end"), (F.col("paths") * F.col("mult")).cast("decimal(38,0)").alias("paths"), *([F.array_append("path", F.col("t")).alias("path")] if with_path else []))
    return _owned(cur)


def track_forward_all(ev: DataFrame, episodes: list[Episode], seg_len: int | None = None, with_path: bool = False, max_matches: int | None = None) -> DataFrame:
    """Every tuple of events that matches, one level after the other.

    With max_matches each producer keeps its earliest next events only: then counts are a lower bound.
    """
    return _by_length(_forward, ev, episodes, seg_len, pruned=False, with_path=with_path, max_matches=max_matches)


def track_forward_pruned(ev: DataFrame, episodes: list[Episode], seg_len: int | None = None) -> DataFrame:
    """For each end the latest start only, with the number of all paths."""
    return _by_length(_forward, ev, episodes, seg_len, pruned=True)


def _windowed(rows: DataFrame, n: int, own: list[Episode], asof: bool) -> DataFrame:
    low, high = own[0].low, own[0].high
    cur = rows.withColumn("s", F.when(F.col("pos") == 0, F.col("t")))
    for i in range(1, n):
        w = W.partitionBy(*KEY).orderBy("t")
        reached = F.when((F.col("pos") == i - 1) & F.col("s").isNotNull(), F.struct(F.col("s").alias("s"), F.col("t").alias("u")))
        if asof:
            best = F.last(reached, ignorenulls=True).over(w.rangeBetween(W.unboundedPreceding, -low[i - 1] - 1))
            ok = best["s"] if high[i - 1] is None else F.when(F.col("t") - best["u"] <= high[i - 1], best["s"])
        else:
            first = W.unboundedPreceding if high[i - 1] is None else -high[i - 1]
            ok = F.max(F.when((F.col("pos") == i - 1), F.col("s"))).over(w.rangeBetween(first, -low[i - 1] - 1))
        cur = cur.withColumn("s", F.when(F.col("pos") == i, ok).otherwise(F.col("s")))
    return _owned(cur.filter((F.col("pos") == n - 1) & F.col("s").isNotNull()).select(*KEY, "is_halo", F.col("s").alias("t_start"), F.col("t").alias("t_end")))


def _by_gaps(ev: DataFrame, episodes: list[Episode], seg_len: int | None, asof: bool) -> DataFrame:
    """Frames need literal bounds, so that there is one pass for each set of gaps."""
    out, groups = None, {}
    for e in episodes:
        groups.setdefault((e.low, e.high), []).append(e)
    for own in groups.values():
        part = _windowed(roles(ev, own, seg_len), len(own[0]), own, asof)
        out = part if out is None else out.unionByName(part)
    return out


def track_window_asof(ev: DataFrame, episodes: list[Episode], seg_len: int | None = None) -> DataFrame:
    """The latest reachable predecessor, by one sort for all levels. The default where few sets of gaps occur."""
    return _by_gaps(ev, episodes, seg_len, True)


def track_window_range(ev: DataFrame, episodes: list[Episode], seg_len: int | None = None) -> DataFrame:
    """The greatest start in a sliding frame; each frame is read again for each row."""
    return _by_gaps(ev, episodes, seg_len, False)


def _union_asof(rows: DataFrame, n: int, _: list[Episode]) -> DataFrame:
    at = lambda i: rows.filter(F.col("pos") == i)
    cur = at(0).select(*KEY, "is_halo", F.col("t").alias("s"), "t")
    for i in range(1, n):
        probes = at(i).select(*KEY, "is_halo", F.lit(None).cast("long").alias("s"), "t", (F.col("t") - F.col("low")).alias("at"), F.lit(0).alias("kind"), "high")
        reached = cur.select(*KEY, "is_halo", "s", "t", F.col("t").alias("at"), F.lit(1).alias("kind"), F.lit(None).cast("long").alias("high"))
        w = W.partitionBy(*KEY).orderBy("at", "kind").rowsBetween(W.unboundedPreceding, -1)
        best = F.last(F.when(F.col("kind") == 1, F.struct("s", F.col("t").alias("u"))), ignorenulls=True).over(w)
        met = probes.unionByName(reached).withColumn("best", best).filter((F.col("kind") == 0) & F.col("best").isNotNull())
        cur = met.filter(F.col("high").isNull() | (F.col("t") - F.col("best")["u"] <= F.col("high"))).select(*KEY, "is_halo", F.col("best")["s"].alias("s"), "t")
    return _owned(cur.select(*KEY, "is_halo", F.col("s").alias("t_start"), F.col("t").alias("t_end")))


def track_union_asof(ev: DataFrame, episodes: list[Episode], seg_len: int | None = None) -> DataFrame:
    """As track_window_asof for any mix of gaps: probes at t - low are merged with what is reached."""
    return _by_length(_union_asof, ev, episodes, seg_len)


def track_backward(ev: DataFrame, episodes: list[Episode], seg_len: int | None = None, pruned: bool = True) -> DataFrame:
    """From the last type to the first: for each start the earliest end, or every match. Time is turned round, so that levels stay as-of windows."""
    turned = ev.withColumn("t", -F.col("t"))
    back = [e.reversed() for e in episodes]
    found = track_union_asof(turned, back, seg_len) if pruned else track_forward_all(turned, back, seg_len)
    return found.select("episode_id", "stream_key", "seg", (-F.col("t_end")).alias("t_start"), (-F.col("t_start")).alias("t_end"))


def track_unconstrained(ev: DataFrame, episodes: list[Episode]) -> DataFrame:
    return track_window_asof(ev, [Episode.of(*e.types, episode_id=e.episode_id) for e in episodes])


def best_starts(times: list[np.ndarray], low: tuple, high: tuple) -> tuple[np.ndarray, np.ndarray]:
    """For each reachable end the latest start; times: sorted instants of each node."""
    s = e = times[0]
    for t, lo, hi in zip(times[1:], low, high, strict=True):
        i = np.searchsorted(e, t - lo, side="left") - 1
        ok = i >= 0
        if hi is not None:
            ok &= (t - e[np.maximum(i, 0)] <= hi) if len(e) else False
        s, e = s[i[ok]], t[ok]
    return s, e


def track_kernel(ev: DataFrame, episodes: list[Episode], seg_len: int | None = None) -> DataFrame:
    """The same in NumPy, a segment of an episode at a time."""
    bounds = {e.episode_id: (e.low, e.high) for e in episodes}

    def found(pdf: pd.DataFrame) -> pd.DataFrame:
        low, high = bounds[pdf["episode_id"].iat[0]]
        times = [np.sort(pdf.loc[pdf["pos"] == i, "t"].to_numpy()) for i in range(len(low) + 1)]
        s, e = best_starts(times, low, high)
        own = np.isin(e, pdf.loc[~pdf["is_halo"], "t"].to_numpy())
        return pd.DataFrame({"episode_id": pdf["episode_id"].iat[0], "stream_key": pdf["stream_key"].iat[0], "seg": pdf["seg"].iat[0], "t_start": s[own], "t_end": e[own]})

    rows = roles(ev, episodes, seg_len).select(*KEY, "pos", "t", "is_halo")
    return rows.groupBy(*KEY).applyInPandas(found, "episode_id string, stream_key string, seg long, t_start long, t_end long")
