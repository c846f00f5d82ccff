"""Overlap removal: the largest number of occurrences of which no two share an instant.

Greedy by end time is optimal. `schedule_segments` is the way for any size: its groups are segments, and what
passes between them is a small table of boundary states.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.storage import written
from ..sources.streams import floor_div

GROUP = ["episode_id", "stream_key"]
#: Before every time there is.
NEVER = -(2**63)


def by_end(occ: DataFrame) -> DataFrame:
    """For each end the latest start: no other occurrence with that end is ever needed."""
    return occ.groupBy(*GROUP, "t_end").agg(F.max("t_start").alias("t_start"))


def greedy(ordered: Column) -> Column:
    """Number of picks from an array of (t_end, t_start) in order."""
    start = F.struct(F.lit(NEVER).alias("e"), F.lit(0).cast("long").alias("n"))
    pick = lambda a, x: F.when(x["t_start"] > a["e"], F.struct(x["t_end"].alias("e"), (a["n"] + 1).alias("n"))).otherwise(a)
    return F.aggregate(ordered, start, pick, lambda a: a["n"])


def schedule_fold(occ: DataFrame, group: list[str] = GROUP) -> DataFrame:
    """One fold for each group, which must fit a task: use it for short streams or on islands."""
    folded = occ.groupBy(*group).agg(F.array_sort(F.collect_list(F.struct("t_end", "t_start"))).alias("o"))
    return folded.select(*group, greedy(F.col("o")).alias("n"))


def schedule_kernel(occ: DataFrame) -> DataFrame:
    return schedule_select(occ).groupBy(*GROUP).agg(F.count("*").alias("n"))


def schedule_select(occ: DataFrame, seg_len: int | None = None) -> DataFrame:
    """The chosen occurrences themselves.

    With seg_len a segment at a time: tables say which end enters each segment, and greedy goes on from there. Without, a
    whole stream is one group.
    """
    if seg_len is not None:
        return _select_segments(occ, seg_len)

    def chosen(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["t_end", "t_start"], ascending=[True, False])
        last, keep = None, []
        for s, e in zip(pdf["t_start"], pdf["t_end"], strict=True):
            keep.append(last is None or s > last)
            last = e if keep[-1] else last
        return pdf[keep]

    rows = by_end(occ).select(*GROUP, "t_start", "t_end")
    return rows.groupBy(*GROUP).applyInPandas(chosen, rows.schema)


def islands(occ: DataFrame) -> DataFrame:
    """Numbers the groups of occurrences that are linked by overlaps."""
    w = W.partitionBy(*GROUP).orderBy("t_start", "t_end")
    before = F.max("t_end").over(w.rowsBetween(W.unboundedPreceding, -1))
    marked = occ.withColumn("_new", F.when(before.isNull() | (F.col("t_start") > before), 1).otherwise(0))
    return marked.withColumn("island", F.sum("_new").over(w.rowsBetween(W.unboundedPreceding, 0))).drop("_new")


def schedule_islands(occ: DataFrame) -> DataFrame:
    """Islands do not touch, so that each is counted alone."""
    return schedule_fold(islands(by_end(occ)), [*GROUP, "island"]).groupBy(*GROUP).agg(F.sum("n").alias("n"))


def schedule_jump(occ: DataFrame, seg_len: int | None = None) -> DataFrame:
    """Successor pointers by an as-of window, then doubling: log2 of the count rounds of equi-joins.

    With seg_len the windows are those of segments, and one row for each segment carries over what they need from their neighbours.
    """
    place = lambda c: F.lit(0).cast("long") if seg_len is None else floor_div(F.col(c), seg_len)
    cut = [*GROUP, "seg"]
    best = written(by_end(occ).withColumn("seg", place("t_end")), "ends")
    # The successor of an end: the first end whose best start is after it. Starts do not fall as ends rise once an end
    # whose start is under an earlier one's is left out, since it can never be picked before that one.
    before = F.max("most").over(W.partitionBy(*GROUP).orderBy("seg").rowsBetween(W.unboundedPreceding, -1))
    tops = best.groupBy(*cut).agg(F.max("t_start").alias("most")).select(*cut, before.alias("_before"))
    w = W.partitionBy(*cut).orderBy("t_end").rowsBetween(W.unboundedPreceding, -1)
    kept = best.withColumn("_top", F.max("t_start").over(w)).join(tops, cut).withColumn("_top", F.greatest("_top", "_before"))
    front = written(kept.filter(F.col("_top").isNull() | (F.col("t_start") > F.col("_top"))).select(*GROUP, "t_end", "t_start"), "front")
    ends = front.select(*GROUP, F.col("t_end").alias("at"), F.lit(1).alias("kind"), F.lit(None).cast("long").alias("to"))
    starts = front.select(*GROUP, F.col("t_start").alias("at"), F.lit(0).alias("kind"), F.col("t_end").alias("to"))
    # Backwards, so that what follows is a frame that only grows: one that shrinks is read again for each row.
    rows = ends.unionByName(starts).withColumn("seg", place("at"))
    later = F.last("least", ignorenulls=True).over(W.partitionBy(*GROUP).orderBy(F.desc("seg")).rowsBetween(W.unboundedPreceding, -1))
    carried = rows.groupBy(*cut).agg(F.min("to").alias("least")).select(*cut, later.alias("_later"))
    after = W.partitionBy(*cut).orderBy(F.desc("at"), F.desc("kind")).rowsBetween(W.unboundedPreceding, -1)
    met = rows.withColumn("next", F.last("to", ignorenulls=True).over(after)).filter("kind = 1").join(carried, cut)
    nxt = met.select(*GROUP, F.col("at").alias("t_end"), F.coalesce("next", "_later").alias("next"))
    jump = written(nxt.withColumn("d", F.lit(1).cast("long")), "jump")
    done = front.groupBy(*GROUP).agg(F.min("t_end").alias("t_end"), F.lit(1).cast("long").alias("n"))
    done = written(done, "chain")
    # Longest jumps first: keep every power of two, then walk down.
    powers = [jump]
    while not powers[-1].filter("next is not null").isEmpty():
        p = powers[-1]
        further = p.join(p.select(*GROUP, F.col("t_end").alias("next"), F.col("next").alias("next2"), F.col("d").alias("d2")), [*GROUP, "next"])
        powers.append(written(further.filter("next2 is not null").select(*GROUP, "t_end", F.col("next2").alias("next"), (F.col("d") + F.col("d2")).alias("d")), "jump"))
    for p in reversed(powers):
        moved = done.join(p.filter("next is not null").select(*GROUP, "t_end", "next", "d"), [*GROUP, "t_end"], "left")
        done = moved.select(*GROUP, F.coalesce("next", "t_end").alias("t_end"), (F.col("n") + F.coalesce("d", F.lit(0))).alias("n"))
    return done.select(*GROUP, "n")


TABLE = "episode_id string, stream_key string, seg long, enter long, leave long, n long"
#: Neighbouring segments whose tables become one in a task.
FAN = 128


def front(start: np.ndarray, end: np.ndarray, ordered: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Occurrences that greedy by end can pick, in order: starts rise strictly and ends do not fall. `ordered`: by end already."""
    if not ordered:
        order = np.lexsort((-start, end))
        start, end = start[order], end[order]
    if not len(start):
        return start, end
    top = np.maximum.accumulate(start)
    keep = np.concatenate([[True], start[1:] > top[:-1]])
    return start[keep], end[keep]


def picks(start: np.ndarray, end: np.ndarray) -> tuple[list[int], list[int]]:
    """For each occurrence of a front: how many greedy picks from it on, itself included, and the end of the last one."""
    m = len(start)
    follow = np.searchsorted(start, end, side="right").tolist()
    number, last = [1] * m, end.tolist()
    for i in range(m - 1, -1, -1):
        if follow[i] < m:
            number[i] += number[follow[i]]
            last[i] = last[follow[i]]
    return number, last


def transfer(start: np.ndarray, end: np.ndarray, border: int) -> list[tuple[int, int, int]]:
    """(enter, leave, n) of a segment that begins at `border`, from the front of the occurrences that end in it.

    A row holds for every entering end from its `enter` up to that of the next row: what matters of an entering end is
    only how many starts lie after it. With n = 0 the entering end leaves as it came.
    """
    enter = [NEVER, *start[start < border].tolist()]
    number, last = picks(start, end)
    first = np.searchsorted(start, np.asarray(enter), side="right").tolist()
    return [(e, last[i], number[i]) if i < len(number) else (e, e, 0) for e, i in zip(enter, first, strict=True)]


def through(seg: np.ndarray, enter: np.ndarray, leave: np.ndarray, n: np.ndarray, states: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Lets states pass the tables of several segments, rows in order of (seg, enter): the states that leave, and the picks."""
    total, edge = np.zeros(len(states), dtype=np.int64), np.flatnonzero(np.concatenate([[True], seg[1:] != seg[:-1], [True]]))
    for i, j in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
        k = i + np.searchsorted(enter[i:j], states, side="right") - 1
        states, total = np.where(n[k] > 0, leave[k], states), total + n[k]
    return states, total


def fold_groups(df: DataFrame, keys: list[str], order: list[str], fold: Callable[[pa.Table], list[tuple]], schema: str) -> DataFrame:
    """fold(rows of one group, in order) for every group; a partition streams through, so that many small groups cost little.

    A group is held whole: callers see to it that it is small.
    """
    names = [x.split()[0] for x in schema.split(", ")]
    types = [{"string": pa.string(), "long": pa.int64(), "int": pa.int32()}[x.split()[1]] for x in schema.split(", ")]

    def starts(t: pa.Table) -> list[int]:
        new = np.zeros(t.num_rows, dtype=bool)
        new[:1] = True
        for k in keys:
            c = t.column(k).combine_chunks()
            c = c.dictionary_encode().indices.to_numpy() if pa.types.is_string(c.type) else c.to_numpy()
            new[1:] |= c[1:] != c[:-1]
        return np.flatnonzero(new).tolist()

    def out(t: pa.Table, edge: list[int]) -> pa.RecordBatch:
        rows = [r for i, j in zip(edge, [*edge[1:], t.num_rows], strict=True) for r in fold(t.slice(i, j - i))]
        return pa.RecordBatch.from_arrays([pa.array(list(c), ty) for c, ty in zip(zip(*rows, strict=True) if rows else [()] * len(names), types, strict=True)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            if b.num_rows:
                t = pa.Table.from_batches([b])
                t = pa.concat_tables([held, t]) if held is not None else t
                edge = starts(t)
                if edge[-1]:
                    yield out(t.slice(0, edge[-1]), edge[:-1])
                held = t.slice(edge[-1])
        if held is not None:
            yield out(held, [0])

    return df.repartition(*keys).sortWithinPartitions(*keys, *order).mapInArrow(run, schema)


def _numbers(t: pa.Table) -> list[np.ndarray]:
    return [t.column(c).to_numpy() for c in ("seg", "enter", "leave", "n")]


def transfer_tables(occ: DataFrame, seg_len: int) -> DataFrame:
    """For each segment the table of what greedy picks in it. An occurrence belongs to the segment of its end."""
    rows = occ.select(*GROUP, floor_div(F.col("t_end"), seg_len).alias("seg"), "t_start", "t_end")

    def table(t: pa.Table) -> list[tuple]:
        e, k, seg = (t.column(c)[0].as_py() for c in (*GROUP, "seg"))
        return [(e, k, seg, *r) for r in transfer(*front(t.column("t_start").to_numpy(), t.column("t_end").to_numpy()), seg * seg_len)]

    return fold_groups(rows, [*GROUP, "seg"], [], table, TABLE)


def compose(tables: DataFrame, seg_len: int, fan: int = FAN) -> DataFrame:
    """One table for each `fan` neighbours: a state for each row that is under the first border of the group."""

    def merged(t: pa.Table) -> list[tuple]:
        seg, enter, leave, n = _numbers(t)
        states = np.unique(np.append(enter[enter < int(seg[0]) * seg_len], NEVER))
        left, total = through(seg, enter, leave, n, states)
        e, k, up = (t.column(c)[0].as_py() for c in (*GROUP, "up"))
        return [(e, k, up, *r) for r in zip(states.tolist(), left.tolist(), total.tolist(), strict=True)]

    return fold_groups(tables.withColumn("up", floor_div(F.col("seg"), fan)), [*GROUP, "up"], ["seg", "enter"], merged, TABLE)


def total_picks(tables: DataFrame) -> DataFrame:
    """The count of a whole stream: only the state before every event enters."""
    total = lambda t: [(*(t.column(c)[0].as_py() for c in GROUP), int(through(*_numbers(t), np.asarray([NEVER]))[1][0]))]
    return fold_groups(tables, GROUP, ["seg", "enter"], total, "episode_id string, stream_key string, n long")


def schedule_segments(occ: DataFrame, seg_len: int) -> DataFrame:
    """Tables for each segment, one for each FAN neighbours, then one pass over these: no round that depends on the data."""
    return total_picks(compose(transfer_tables(occ, seg_len), seg_len))


def entering(tables: DataFrame) -> DataFrame:
    """The end that enters each segment, if nothing was picked before the first one. A task passes one stream's tables, not its occurrences."""

    def states(t: pa.Table) -> list[tuple]:
        (seg, enter, leave, n), state, out = _numbers(t), NEVER, []
        edge = np.flatnonzero(np.concatenate([[True], seg[1:] != seg[:-1], [True]]))
        key = tuple(t.column(c)[0].as_py() for c in GROUP)
        for i, j in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
            out.append((*key, int(seg[i]), state))
            k = i + int(np.searchsorted(enter[i:j], state, side="right")) - 1
            state = int(leave[k]) if n[k] else state
        return out

    return fold_groups(tables, GROUP, ["seg", "enter"], states, "episode_id string, stream_key string, seg long, state long")


def _select_segments(occ: DataFrame, seg_len: int) -> DataFrame:
    rows = occ.select(*GROUP, floor_div(F.col("t_end"), seg_len).alias("seg"), "t_start", "t_end")
    rows = rows.join(entering(transfer_tables(occ, seg_len)), [*GROUP, "seg"])

    def chosen(t: pa.Table) -> list[tuple]:
        start, end = front(t.column("t_start").to_numpy(), t.column("t_end").to_numpy())
        key, out = tuple(t.column(c)[0].as_py() for c in GROUP), []
        i = int(np.searchsorted(start, t.column("state")[0].as_py(), side="right"))
        while i < len(start):
            out.append((*key, int(start[i]), int(end[i])))
            i = int(np.searchsorted(start, end[i], side="right"))
        return out

    return fold_groups(rows, [*GROUP, "seg"], [], chosen, "episode_id string, stream_key string, t_start long, t_end long")
