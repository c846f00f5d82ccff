"""Segments of a stream in Arrow: levels of tracking, the three compactions and overlap removal in one task for each segment.

One shuffle by (stream, segment) serves every episode and every level. What leaves a segment is its occurrences, its
table of boundary states, or what its levels have cost.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.model import Episode, span
from ..plans.storage import written
from ..sources.streams import segment
from .scheduling import GROUP, TABLE, compose, fold_groups, front, total_picks, transfer
from .tracking import best_starts

WAYS = ("unordered", "padded", "count_scan_write", "count_scan_write_backward")
LEVELS = "episode_id string, stream_key string, seg long, way string, level int, producers long, matches long, slots long, tests long, sorted long, groups long, divergent long"
#: Producers that run side by side, as in a group of lanes of one instruction stream.
LANES = 32


def layout(ev: DataFrame, episodes: list[Episode], seg_len: int) -> DataFrame:
    """stream_key, seg, event_type, t, is_halo: what counting these episodes by segments needs."""
    reach = span(episodes)
    if reach is None:
        raise ValueError("segments with a halo need bounded gaps")
    own = ev.filter(F.col("event_type").isin(*sorted({t for e in episodes for t in e.types})))
    return segment(own.select("stream_key", "event_type", "t"), seg_len, reach)


def _times(t: pa.Table) -> dict[str, np.ndarray]:
    """The sorted instants of each type."""
    codes = t.column("event_type").combine_chunks().dictionary_encode()
    codes = codes.combine_chunks() if isinstance(codes, pa.ChunkedArray) else codes
    at, code = t.column("t").to_numpy(), codes.indices.to_numpy()
    return {name: np.unique(at[code == k]) for k, name in enumerate(codes.dictionary.to_pylist())}


def _nodes(times: dict[str, np.ndarray], e: Episode) -> list[np.ndarray]:
    none = np.zeros(0, dtype=np.int64)
    return [times.get(ty, none) for ty in e.types]


def segment_tables(ev: DataFrame, episodes: list[Episode], seg_len: int, first: bool = False) -> DataFrame:
    """Tracking (the latest start of each end) and the table of boundary states, for all episodes in one pass over a segment.

    With `first` also the end of the first pick.
    """

    def made(t: pa.Table) -> list[tuple]:
        key, seg = t.column("stream_key")[0].as_py(), t.column("seg")[0].as_py()
        times, border, rows = _times(t), seg * seg_len, []
        for e in episodes:
            start, end = best_starts(_nodes(times, e), e.low, e.high)
            own = end >= border
            if own.any():
                start, end = front(start[own], end[own], ordered=True)
                table = transfer(start, end, border)
                if first:
                    at = np.searchsorted(start, [r[0] for r in table], side="right").tolist()
                    table = [(*r, int(end[i]) if i < len(end) else None) for r, i in zip(table, at, strict=True)]
                rows += [(e.episode_id, key, seg, *r) for r in table]
        return rows

    return fold_groups(layout(ev, episodes, seg_len), ["stream_key", "seg"], [], made, TABLE + ", first long" * first)


def count_segments(ev: DataFrame, episodes: list[Episode], seg_len: int) -> DataFrame:
    """episode_id, stream_key, n of streams that have an occurrence."""
    return total_picks(compose(segment_tables(ev, episodes, seg_len), seg_len))


def _ranges(lo: np.ndarray, count: np.ndarray) -> np.ndarray:
    """lo[i], lo[i] + 1, ... count[i] places for each i, one after the other."""
    offset = np.cumsum(count) - count
    return np.arange(int(count.sum())) - np.repeat(offset - lo, count)


def _unordered(lo: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Blocks of producers reserve room one after the other, in no special order; here every other block comes first."""
    block = np.arange(len(lo)) // 256
    turn = np.lexsort((np.arange(len(lo)), block, block % 2))
    return turn[np.repeat(np.arange(len(lo)), count[turn])], _ranges(lo[turn], count[turn])


def _padded(lo: np.ndarray, count: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Each producer fills `capacity` slots; all are scanned for the ones in use."""
    slots = lo[:, None] + np.arange(capacity)[None, :]
    used = np.arange(capacity)[None, :] < count[:, None]
    producer, slot = np.nonzero(used)
    return producer, slots[producer, slot]


def _scanned(lo: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each producer writes at the exclusive sum of the counts before it: dense and in the producers' order."""
    total = np.cumsum(count)
    producer, place = np.empty(int(total[-1]) if len(total) else 0, dtype=np.int64), _ranges(lo, count)
    producer[:] = np.repeat(np.arange(len(lo)), count)
    return producer, place


def track_levels(times: list[np.ndarray], e: Episode, way: str, border: int, capacity: int) -> tuple[np.ndarray, np.ndarray, list[tuple]]:
    """Every match of an episode that ends at `border` or later, and for each level what the way has cost.

    Forward from the first node; backward from the last one, with the producers in order of their ends, so that the
    result needs no sort. Padded slots that do not suffice are doubled and filled again. Costs: level, producers, matches, slots, tests of the gap,
    rows sorted, groups of LANES producers, and how many of these have unequal counts.
    """
    back = way == "count_scan_write_backward"
    n, costs = len(e), []
    cur = times[-1][times[-1] >= border] if back else times[0]
    other = cur.copy()  # the end that is kept while the levels walk on
    for i in range(1, n):
        node = n - 1 - i if back else i
        low, high = (e.low[node], e.high[node]) if back else (e.low[i - 1], e.high[i - 1])
        t = times[node]
        if back:
            lo, hi = np.searchsorted(t, cur - high, side="left"), np.searchsorted(t, cur - low, side="left")
            examined = np.searchsorted(t, cur, side="left") - lo + 1
        else:
            lo, hi = np.searchsorted(t, cur + low, side="right"), np.searchsorted(t, cur + high, side="right")
            examined = hi - np.searchsorted(t, cur, side="right") + 1  # every later event up to the first beyond the bound
        count = np.maximum(hi - lo, 0)
        searches, slots = (2 if way.startswith("count_scan_write") else 1), 0
        if way == "unordered":
            producer, place = _unordered(lo, count)
        elif way == "padded":
            while len(count) and count.max() > capacity:
                capacity *= 2
                searches += 1
            producer, place = _padded(lo, count, capacity)
            slots = capacity * len(lo)
        else:
            producer, place = _scanned(lo, count)
        groups = -(-len(count) // LANES)
        lanes = np.pad(count, (0, groups * LANES - len(count)), mode="edge").reshape(groups, LANES) if len(count) else np.zeros((0, 1))
        costs.append((i, len(count), len(producer), slots, searches * int(np.maximum(examined, 0).sum()), 0, groups, int((lanes.min(axis=1) != lanes.max(axis=1)).sum()) if groups else 0))
        cur, other = t[place], other[producer]
    start, end = (cur, other) if back else (other, cur)
    if not back:
        own = end >= border
        start, end = start[own], end[own]
        costs.append((n, 0, 0, 0, 0, len(end), 0, 0))
        order = np.lexsort((start, end))
        start, end = start[order], end[order]
    return start, end, costs


def rounds_run(ev: DataFrame, episodes: list[Episode], seg_len: int) -> DataFrame:
    """episode_id, stream_key, seg, rounds: how many levels of tracking had a producer. The halo holds an occurrence's first nodes, so that the most of all segments is that of the stream."""

    def made(t: pa.Table) -> list[tuple]:
        key, seg = t.column("stream_key")[0].as_py(), t.column("seg")[0].as_py()
        times, rows = _times(t), []
        for e in episodes:
            nodes = _nodes(times, e)
            own = [i for i in range(1, len(e)) if len(best_starts(nodes[:i], e.low[: i - 1], e.high[: i - 1])[1])]
            rows.append((e.episode_id, key, seg, len(own)))
        return rows

    return fold_groups(layout(ev, episodes, seg_len), ["stream_key", "seg"], [], made, "episode_id string, stream_key string, seg long, rounds long")


def _by_segment(ev: DataFrame, episodes: list[Episode], seg_len: int, ways: tuple[str, ...], capacity: int, rows_of, schema: str) -> DataFrame:
    def made(t: pa.Table) -> list[tuple]:
        key, seg = t.column("stream_key")[0].as_py(), t.column("seg")[0].as_py()
        times, out = _times(t), []
        for e in episodes:
            nodes = _nodes(times, e)
            for way in ways:
                start, end, costs = track_levels(nodes, e, way, seg * seg_len, capacity)
                out += [(e.episode_id, key, seg, way, *r) for r in rows_of(start, end, costs, seg * seg_len)]
        return out

    return fold_groups(layout(ev, episodes, seg_len), ["stream_key", "seg"], [], made, schema)


def track_compacted(ev: DataFrame, episodes: list[Episode], seg_len: int, way: str, capacity: int = 64) -> DataFrame:
    """Every match (one row for each path) with its dense place `index` in the segment, in order of ends."""

    def made(t: pa.Table) -> pa.Table:
        key, seg = t.column("stream_key")[0].as_py(), t.column("seg")[0].as_py()
        times, parts = _times(t), []
        for e in episodes:
            start, end, _ = track_levels(_nodes(times, e), e, way, seg * seg_len, capacity)
            parts.append(pa.Table.from_arrays([pa.array([e.episode_id] * len(start), pa.string()), pa.array([key] * len(start), pa.string()), pa.array(np.full(len(start), seg)), pa.array(start), pa.array(end), pa.array(np.arange(len(start)))], ["episode_id", "stream_key", "seg", "t_start", "t_end", "index"]))
        return pa.concat_tables(parts)

    return layout(ev, episodes, seg_len).groupBy("stream_key", "seg").applyInArrow(made, "episode_id string, stream_key string, seg long, t_start long, t_end long, index long")


def level_costs(ev: DataFrame, episodes: list[Episode], seg_len: int, ways: tuple[str, ...] = WAYS, capacity: int = 64) -> DataFrame:
    """What each level of each way has cost in each segment (LEVELS)."""
    return _by_segment(ev, episodes, seg_len, ways, capacity, lambda s, e, costs, border: costs, LEVELS)


def count_compacted(ev: DataFrame, episodes: list[Episode], seg_len: int, ways: tuple[str, ...] = WAYS, capacity: int = 64) -> DataFrame:
    """episode_id, stream_key, way, n (without overlap) and paths (all matches), by full tracking in each way."""

    def rows_of(start, end, costs, border) -> Iterator[tuple]:
        tables = transfer(*front(start, end, ordered=True), border) if len(start) else []
        return [(len(start) if k == 0 else 0, *r) for k, r in enumerate(tables)]

    schema = "episode_id string, stream_key string, seg long, way string, paths long, enter long, leave long, n long"
    tables = _by_segment(ev, episodes, seg_len, ways, capacity, rows_of, schema)
    # The way is part of the episode's name while tables are composed; the small tables serve two sums.
    named = written(tables.withColumn("episode_id", F.concat_ws("\x1f", "episode_id", "way")).drop("way"), "ways")
    n = total_picks(compose(named.drop("paths"), seg_len))
    paths = named.groupBy(*GROUP).agg(F.sum("paths").alias("paths"))
    part = F.split("episode_id", "\x1f")
    found = n.join(paths, GROUP).select(F.element_at(part, 1).alias("episode_id"), "stream_key", F.element_at(part, 2).alias("way"), "n", "paths")
    each = F.explode(F.array(*[F.struct(F.lit(e.episode_id).alias("episode_id"), F.lit(w).alias("way")) for e in episodes for w in ways]))
    zeros = ev.select("stream_key").distinct().select(each.alias("x"), "stream_key").select("x.episode_id", "stream_key", "x.way", F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("paths"))
    return zeros.unionByName(found).groupBy("episode_id", "stream_key", "way").agg(F.sum("n").alias("n"), F.sum("paths").alias("paths"))
