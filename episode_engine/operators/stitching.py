"""Segment-parallel counting: several machines for each segment, stitched where their boundary occurrences agree."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.model import Episode, span
from ..plans.storage import written
from ..sources.streams import floor_div, segment
from .scheduling import FAN, GROUP, NEVER, TABLE, through
from .segments import count_segments, segment_tables
from .serial import Machine, _all_counts, instants

SUMMARY = "episode_id string, stream_key string, seg long, machine int, first_end long, prev_end long, last_end long, n long"
ENDS = ["first_end", "prev_end", "last_end"]


def _of_frame(f: Callable[[pd.DataFrame], pd.DataFrame]) -> Callable[[pd.DataFrame], pd.DataFrame]:
    """A function of one argument: Spark would pass the group's key to a first one of two."""
    return lambda pdf: f(pdf)


def segment_map(ev: DataFrame, episodes: list[Episode], seg_len: int) -> DataFrame:
    """For each segment one machine more than gaps: machine j starts the sum of j bounds before the left border.

    first_end is its first completion after the left border, prev_end the last before the right one, last_end the first after that,
    n the completions in (first_end, last_end]. Completions are looked for within two spans after the right border; null: none there.
    All episodes are run in one pass over a segment.
    """
    reach = span(episodes)
    if reach is None:
        raise ValueError("segment machines need bounded gaps")

    plays = [{ty: [i for i in range(len(e) - 1, -1, -1) if e.types[i] == ty] for ty in set(e.types)} for e in episodes]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        key, seg, rows = pdf["stream_key"].iat[0], int(pdf["seg"].iat[0]), []
        left, right = seg * seg_len, (seg + 1) * seg_len
        every = instants(pdf["t"].tolist(), pdf["event_type"].tolist())
        for e, can in zip(episodes, plays, strict=True):
            near = [(t, types) for t, types in every if left - e.span <= t < right + 2 * e.span and not types.isdisjoint(can)]
            seen, before = [(t, can[next(iter(types))] if len(types) == 1 else sorted({i for ty in types for i in can.get(ty, ())}, reverse=True)) for t, types in near], 0
            for j in range(len(e) if seen else 0):
                m, ends = Machine(e, True), []
                for t, nodes in seen:
                    if t > left - before - 1 and m.reach(t, nodes):
                        ends.append(t)
                        if t >= right:
                            break
                inside = [x for x in ends if x >= left]
                first = inside[0] if inside else None
                last = inside[-1] if inside and inside[-1] >= right else None
                prev = next((x for x in reversed(inside) if x < right), None)
                rows.append((e.episode_id, key, seg, j, first, prev, last, max(0, len(inside) - 1)))
                before += e.high[j] if j < len(e.high) else 0
        return pd.DataFrame(rows, columns=["episode_id", "stream_key", "seg", "machine", *ENDS, "n"]).astype(dict.fromkeys(ENDS, "Int64"))

    own = ev.filter(F.col("event_type").isin(*sorted({t for e in episodes for t in e.types}))).select("stream_key", "event_type", "t")
    return segment(own, seg_len, reach, 2 * reach).groupBy("stream_key", "seg").applyInPandas(run, SUMMARY)


#: A machine's (first_end, prev_end, last_end, n).
Run = tuple[int | None, int | None, int | None, int]


def follows(first: int | None, last: int | None, border: int, reach: int) -> bool:
    """Whether a machine whose first completion is `first` goes on where one left with `last` at `border`.

    Without a completion in two spans after the border all machines hold the same events from then on.
    """
    return first == last if last is not None else first is None or first >= border + 2 * reach


def join_neighbours(left: list[Run], right: list[Run], border: int, reach: int) -> list[Run] | None:
    """Each machine of the left side with the one of the right side that goes on from its last end; None where one finds none."""
    out = []
    for first, prev, last, n in left:
        met = next((r for r in right if follows(r[0], last, border, reach)), None)
        if met is None:
            return None
        late = last is None and met[0] is not None  # counted by neither side so far
        out.append((met[0] if first is None else first, prev if met[1] is None else met[1], met[2], n + met[3] + (late and first is not None)))
    return out


def _filled(df: DataFrame) -> DataFrame:
    """Missing ends as NEVER: pandas would turn a column with nulls into floating numbers."""
    return df.withColumns({c: F.coalesce(c, F.lit(NEVER)) for c in ENDS})


def _runs(g: pd.DataFrame) -> list[Run]:
    return [(*(None if x == NEVER else x for x in row[:3]), row[3]) for row in zip(*(g[x].tolist() for x in (*ENDS, "n")), strict=True)]


def segment_concat(summaries: DataFrame, episodes: list[Episode], seg_len: int, fan: int = 128) -> DataFrame:
    """Neighbours are merged pair by pair, in rounds that halve their number: first those of `fan` segments in a task, then what is left.

    episode_id, stream_key, lo, hi (first and last segment), machine (0, 1, ... of the leftmost segment), and its ends and n.
    A border that no machine crosses stays open; both sides are then in the result.
    """
    reach = {e.episode_id: e.span for e in episodes}

    def merged(pdf: pd.DataFrame) -> pd.DataFrame:
        e, key = pdf["episode_id"].iat[0], pdf["stream_key"].iat[0]
        parts = [(_runs(g), int(lo), int(hi)) for (lo, hi), g in pdf.sort_values(["lo", "machine"]).groupby(["lo", "hi"])]
        joined = True
        while len(parts) > 1 and joined:
            nxt, i, joined = [], 0, False
            while i < len(parts):
                a, b = parts[i], parts[i + 1] if i + 1 < len(parts) else None
                both = join_neighbours(a[0], b[0], (a[2] + 1) * seg_len, reach[e]) if b else None
                nxt.append(a if both is None else (both, a[1], b[2]))
                joined, i = joined or both is not None, i + (1 if both is None else 2)
            parts = nxt
        rows = [(e, key, lo, hi, j, *r) for rs, lo, hi in parts for j, r in enumerate(rs)]
        return pd.DataFrame(rows, columns=["episode_id", "stream_key", "lo", "hi", "machine", *ENDS, "n"]).astype(dict.fromkeys(ENDS, "Int64"))

    schema = "episode_id string, stream_key string, lo long, hi long, machine int, first_end long, prev_end long, last_end long, n long"
    cur = summaries.select(*GROUP, F.col("seg").alias("lo"), F.col("seg").alias("hi"), "machine", *ENDS, "n")
    some = _filled(cur).groupBy(*GROUP, floor_div(F.col("lo"), fan)).applyInPandas(_of_frame(merged), schema)
    return _filled(some).groupBy(*GROUP).applyInPandas(_of_frame(merged), schema)


def cross_open_borders(parts: list[tuple[list[Run], int, int]], tables: list[np.ndarray], seg_len: int, reach: int) -> tuple[int, int]:
    """The count of a stream from merged parts in order, and how many of them exact tables had to count.

    tables: seg, enter, leave, n, first (end of the first pick) of the parts after the first one, in order. Machines go on
    after such a part as soon as one has the first pick as its first end.
    """
    n, fell, last, prev, state = 0, 0, None, None, None  # a state: exact tables hold the count
    for k, (runs, lo, hi) in enumerate(parts):
        run, border = None, lo * seg_len
        if k == 0:  # nothing was counted before: the machine that starts first has seen all there is
            run, late = runs[-1], True
        elif state is None:
            run, late = next((r for r in runs if follows(r[0], last, border, reach)), None), last is None
        if run is None:
            i, j = np.searchsorted(tables[0], lo), np.searchsorted(tables[0], hi, side="right")
            seg, enter, leave, number, first = (x[i:j] for x in tables)
            if state is None:
                n, state = n - (last is not None), NEVER if prev is None else prev
            elif len(seg):
                at = np.searchsorted(enter[seg == seg[0]], state, side="right") - 1
                run, late = (next((r for r in runs if r[0] == first[at]), None) if number[at] else None), True
        if run is not None:
            n, last, prev, state = n + run[3] + (late and run[0] is not None), run[2], prev if run[1] is None else run[1], None
        else:
            out, total = through(seg, enter, leave, number, np.asarray([state]))
            n, state, fell = n + int(total[0]), int(out[0]), fell + 1
    return n, fell


def machine_counts(ev: DataFrame, episodes: list[Episode], seg_len: int) -> DataFrame:
    """episode_id, stream_key, n, by_tables: counts by machines, and how many parts exact tables had to count as no machine crossed the border before them."""
    parts = written(segment_concat(segment_map(ev, episodes, seg_len), episodes, seg_len), "parts")
    first = parts.groupBy(*GROUP).agg(F.min("lo").alias("least"))
    after = written(parts.join(first, GROUP).filter("lo > least").select(*GROUP, "lo", "hi").distinct(), "after")
    reach = {e.episode_id: e.span for e in episodes}
    rows = parts.select(*GROUP, "lo", "hi", "machine", *ENDS, "n")
    if not after.isEmpty():
        tables = segment_tables(ev, episodes, seg_len, first=True).join(after, GROUP).filter("seg between lo and hi")
        rows = rows.unionByName(tables.select(*GROUP, F.col("seg").alias("lo"), F.col("seg").alias("hi"), F.lit(-1).alias("machine"), F.col("enter").alias("first_end"), F.col("leave").alias("prev_end"), F.col("first").alias("last_end"), "n"))

    def total(pdf: pd.DataFrame) -> pd.DataFrame:
        exact = pdf[pdf["machine"] < 0].sort_values(["lo", "first_end"])
        tables = [exact[c].to_numpy(dtype=np.int64) for c in ("lo", "first_end", "prev_end", "n", "last_end")]
        own = [(_runs(g), int(lo), int(hi)) for (lo, hi), g in pdf[pdf["machine"] >= 0].sort_values(["lo", "machine"]).groupby(["lo", "hi"])]
        n, fell = cross_open_borders(own, tables, seg_len, reach[pdf["episode_id"].iat[0]])
        return pd.DataFrame({"episode_id": [pdf["episode_id"].iat[0]], "stream_key": [pdf["stream_key"].iat[0]], "n": [n], "by_tables": [fell]})

    return _filled(rows).groupBy(*GROUP).applyInPandas(_of_frame(total), "episode_id string, stream_key string, n long, by_tables long")


def count_segment_machines(ev: DataFrame, episodes: list[Episode], seg_len: int) -> DataFrame:
    return _all_counts(machine_counts(ev, episodes, seg_len), ev, episodes)


def count_segment_exact(ev: DataFrame, episodes: list[Episode], seg_len: int) -> DataFrame:
    """For every end that may enter a segment: the end that leaves it and the count. Right for any length of segments."""
    return _all_counts(count_segments(ev, episodes, seg_len), ev, episodes)


def count_segment_unconstrained(ev: DataFrame, episodes: list[Episode], seg_len: int) -> DataFrame:
    """Without bounds the state is how many nodes are matched: a table of N rows for each segment, no halo."""

    def table(pdf: pd.DataFrame) -> pd.DataFrame:
        rows, key, seg = [], pdf["stream_key"].iat[0], pdf["seg"].iat[0]
        for e in episodes:
            own = pdf["event_type"].isin(set(e.types))
            seen = instants(pdf.loc[own, "t"].tolist(), pdf.loc[own, "event_type"].tolist())
            for state in range(len(e) if seen else 0):
                at, n = state, 0
                for _, types in seen:
                    if e.types[at] in types:
                        at += 1
                        if at == len(e):
                            at, n = 0, n + 1
                rows.append((e.episode_id, key, seg, state, at, n))
        return pd.DataFrame(rows, columns=["episode_id", "stream_key", "seg", "enter", "leave", "n"])

    def merged(pdf: pd.DataFrame) -> pd.DataFrame:
        """Tables of neighbours, one after the other: N states pass them all."""
        own = pdf.sort_values(["seg", "enter"])
        states = np.arange(int(own["enter"].max()) + 1)
        at, total = states.copy(), np.zeros(len(states), dtype=np.int64)
        for _, g in own.groupby("seg"):
            leave, n = g["leave"].to_numpy(), g["n"].to_numpy()
            total, at = total + n[at], leave[at]
        first = own.iloc[0]
        return pd.DataFrame({"episode_id": first["episode_id"], "stream_key": first["stream_key"], "seg": first["up"], "enter": states, "leave": at, "n": total})

    own = ev.filter(F.col("event_type").isin(*sorted({t for e in episodes for t in e.types}))).withColumn("seg", floor_div(F.col("t"), seg_len))
    cur = own.groupBy("stream_key", "seg").applyInPandas(_of_frame(table), TABLE)
    for up in (floor_div(F.col("seg"), FAN), F.lit(0).cast("long")):
        cur = cur.withColumn("up", up).groupBy(*GROUP, "up").applyInPandas(_of_frame(merged), TABLE)
    return _all_counts(cur.filter("enter = 0").select(*GROUP, "n"), ev, episodes)
