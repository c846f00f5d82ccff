"""The serial counter: a state machine that keeps, for each node, the instants that have reached it."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.model import Episode
from .tracking import roles

COUNT = "episode_id string, stream_key string, n long"


class Machine:
    """Counts occurrences that do not overlap, one instant after another; state is lists of instants by node."""

    def __init__(self, e: Episode, evict: bool = False) -> None:
        self.tests = 0  # of the gap
        self.e, self.evict, self.n, self.last, self.lists = e, evict, 0, None, [deque() for _ in e.types]

    def feed(self, t: int, types: set[str]) -> bool:
        """All types seen at instant t, which never comes back; true if an occurrence was completed."""
        return self.reach(t, [i for i in range(len(self.e) - 1, -1, -1) if self.e.types[i] in types])

    def reach(self, t: int, nodes: Iterable[int]) -> bool:
        """The same for the nodes, last one first, that the types seen at instant t can play."""
        e = self.e
        if self.last is not None and t <= self.last:
            return False
        for i in nodes:
            if i:
                lo, hi = e.low[i - 1], e.high[i - 1]
                before = self.lists[i - 1]
                if self.evict and hi is not None:
                    while before and t - before[0] > hi:
                        before.popleft()
                if not self._reached(before, t, lo, hi):
                    continue
            if i == len(e) - 1:
                self.n, self.last, self.lists = self.n + 1, t, [deque() for _ in e.types]
                return True
            self.lists[i].append(t)
        return False

    def _reached(self, before: deque, t: int, lo: int, hi: int | None) -> bool:
        for u in reversed(before):
            self.tests += 1
            if lo < t - u:
                return hi is None or t - u <= hi  # earlier ones are farther off
        return False


def count_instants(e: Episode, instants: Iterable[tuple[int, set[str]]], evict: bool = False) -> int:
    m = Machine(e, evict)
    for t, types in instants:
        m.feed(t, types)
    return m.n


def instants(t: Iterable[int], types: Iterable[str]) -> list[tuple[int, set[str]]]:
    out: dict[int, set[str]] = {}
    for a, b in zip(t, types, strict=True):
        out.setdefault(a, set()).add(b)
    return sorted(out.items())


def _all_counts(counts: DataFrame, ev: DataFrame, episodes: list[Episode]) -> DataFrame:
    """With a zero for each episode and stream without an occurrence: zeros are added, which needs no join."""
    ids = F.split(F.lit("\x1f".join(e.episode_id for e in episodes)), "\x1f")  # one literal, however many there are
    zeros = ev.select("stream_key").distinct().select(F.explode(ids).alias("episode_id"), "stream_key", F.lit(0).cast("long").alias("n"))
    return zeros.unionByName(counts.select("episode_id", "stream_key", "n")).groupBy("episode_id", "stream_key").agg(F.sum("n").alias("n"))


def count_serial(ev: DataFrame, episodes: list[Episode], evict: bool = False, workers: int | None = None) -> DataFrame:
    """One task for each stream and episode: the baseline that all other counters must equal."""
    types = sorted({t for e in episodes for t in e.types})
    code = {ty: c for c, ty in enumerate(types)}
    plays = [{code[ty]: tuple(i for i in range(len(e) - 1, -1, -1) if e.types[i] == ty) for ty in set(e.types)} for e in episodes]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows in order of (episode, stream, time) pass the machine one by one: no stream is held."""
        m, group, at, nodes = None, None, None, ()
        for b in batches:
            done, k = [], b.column("k").to_numpy()
            key, t, c = b.column("stream_key").dictionary_encode(), b.column("t").to_numpy(), b.column("code").to_numpy()
            place = key.indices.to_numpy()
            edge = [0, *(np.flatnonzero((k[1:] != k[:-1]) | (place[1:] != place[:-1])) + 1).tolist(), len(k)] if len(k) else []
            for i, j in zip(edge[:-1], edge[1:], strict=True):
                if (own := (int(k[i]), key.dictionary[int(place[i])].as_py())) != group:
                    if group is not None:
                        m.reach(at, nodes)
                        done.append((episodes[group[0]].episode_id, group[1], m.n))
                    m, group, at, nodes = Machine(episodes[own[0]], evict), own, int(t[i]), ()
                can = plays[own[0]]
                for now, ty in zip(t[i:j].tolist(), c[i:j].tolist(), strict=True):
                    if now != at:
                        m.reach(at, nodes)
                        at, nodes = now, can[ty]
                    elif nodes != can[ty]:
                        nodes = tuple(sorted({*nodes, *can[ty]}, reverse=True))
            yield _count_rows(done)
        if group is not None:
            m.reach(at, nodes)
            yield _count_rows([(episodes[group[0]].episode_id, group[1], m.n)])

    wanted = ev.sparkSession.createDataFrame([(k, ty, code[ty]) for k, e in enumerate(episodes) for ty in sorted(set(e.types))], "k int, event_type string, code int")
    rows = ev.filter(F.col("event_type").isin(*types)).join(F.broadcast(wanted), "event_type").select("k", "stream_key", "t", "code")
    rows = rows.repartition(workers, "k", "stream_key") if workers else rows.repartition("k", "stream_key")
    return _all_counts(rows.sortWithinPartitions("k", "stream_key", "t").mapInArrow(run, COUNT), ev, episodes)


def _count_rows(rows: list[tuple[str, str, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], ty) for i, ty in enumerate((pa.string(), pa.string(), pa.int64()))], ["episode_id", "stream_key", "n"])


def count_episode_parallel(ev: DataFrame, episodes: list[Episode]) -> DataFrame:
    """A worker for each episode: cores are idle where there are fewer episodes. Very many share four tasks a core."""
    return count_serial(ev, episodes, evict=True, workers=min(len(episodes), 4 * ev.sparkSession.sparkContext.defaultParallelism))


def count_serial_unconstrained(ev: DataFrame, episodes: list[Episode]) -> DataFrame:
    """Without bounds one pointer is the whole state."""
    by_id = {e.episode_id: e for e in episodes}

    def count(pdf: pd.DataFrame) -> pd.DataFrame:
        e, at, n, last = by_id[pdf["episode_id"].iat[0]], 0, 0, None
        for t, types in instants(pdf["t"].tolist(), pdf["event_type"].tolist()):
            if t != last and e.types[at] in types:
                at, last = at + 1, t
                if at == len(e):
                    at, n = 0, n + 1
        return pd.DataFrame({"episode_id": [e.episode_id], "stream_key": [pdf["stream_key"].iat[0]], "n": [n]})

    rows = roles(ev, [Episode.of(*e.types, episode_id=e.episode_id) for e in episodes]).select("episode_id", "stream_key", "event_type", "t")
    return _all_counts(rows.groupBy("episode_id", "stream_key").applyInPandas(count, COUNT), ev, episodes)


def count_serial_fold(ev: DataFrame, episodes: list[Episode]) -> DataFrame:
    """The machine as a fold of SQL functions: no Python on the executors. For streams that fit a task."""
    out = None
    for e in episodes:
        n = len(e)
        own = ev.filter(F.col("event_type").isin(*set(e.types))).groupBy("stream_key", "t").agg(F.collect_set("event_type").alias("types"))
        seq = own.groupBy("stream_key").agg(F.array_sort(F.collect_list(F.struct("t", "types"))).alias("seq"))
        empty = F.array().cast("array<bigint>")
        start = F.struct(F.lit(0).cast("long").alias("n"), *[empty.alias(f"l{i}") for i in range(n - 1)])

        def within(t, lo, hi):
            return lambda u: (t - u > lo) & (F.lit(True) if hi is None else t - u <= hi)

        def step(a, x, e=e, n=n, empty=empty, within=within):
            can = []
            for i in range(n):
                here = F.array_contains(x["types"], e.types[i])
                if i:
                    lo, hi = e.low[i - 1], e.high[i - 1]
                    here = here & F.exists(a[f"l{i - 1}"], within(x["t"], lo, hi))
                can.append(here)
            full = F.struct((a["n"] + 1).alias("n"), *[empty.alias(f"l{i}") for i in range(n - 1)])

            def grown(i):
                more = F.when(can[i], F.array_append(a[f"l{i}"], x["t"])).otherwise(a[f"l{i}"])
                return more if e.high[i] is None else F.filter(more, lambda u: x["t"] - u <= e.high[i])

            return F.when(can[-1], full).otherwise(F.struct(a["n"].alias("n"), *[grown(i).alias(f"l{i}") for i in range(n - 1)]))

        one = seq.select(F.lit(e.episode_id).alias("episode_id"), "stream_key", F.aggregate("seq", start, lambda a, x: step(a, x), lambda a: a["n"]).alias("n"))
        out = one if out is None else out.unionByName(one)
    return _all_counts(out, ev, episodes)
