"""Three ways from producers' lists of next events to one dense list, and the prefix scan that one of them needs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.model import Episode, expand_roles
from ..plans.storage import written
from .tracking import KEY, _pairs, roles


def _nodes(ev: DataFrame, episode: Episode, seg_len: int | None, backward: bool) -> DataFrame:
    """Events with the levels that they can play. Backward, time is turned round and the last node is level 0; segments and halos stay."""
    if not backward:
        return roles(ev, [episode], seg_len)
    own = roles(ev, [episode], seg_len).select("stream_key", "event_type", "t", "mult", "seg", "is_halo").distinct()
    return expand_roles(own, [episode.reversed()]).withColumn("t", -F.col("t"))


def seeds(ev: DataFrame, episode: Episode, seg_len: int | None = None, backward: bool = False) -> DataFrame:
    """Producers of the first level, numbered from 0 in each segment by `index`: events of the first type in order of time.

    Backward: events of the last type that the segment owns, in order of (true) time, so that all that follows is in order of ends.
    """
    first = _nodes(ev, episode, seg_len, backward).filter("pos = 0")
    first = first.filter("not is_halo") if backward else first
    rows = first.select(*KEY, "is_halo", F.col("t").alias("t_start"), F.col("t").alias("t_end"))
    order = F.col("t_start").desc() if backward else F.col("t_start")
    return rows.withColumn("index", F.row_number().over(W.partitionBy(*KEY).orderBy(order)).cast("long") - 1)


def level(cur: DataFrame, ev: DataFrame, episode: Episode, i: int, seg_len: int | None = None, backward: bool = False, tested: bool = False) -> DataFrame:
    """What a level finds: for each producer `index` its next events t; with `tested` also the events that the gap turns down (`met`)."""
    nodes = _nodes(ev, episode, seg_len, backward).filter(F.col("pos") == i)
    found = _pairs(cur, nodes, [episode.reversed() if backward else episode], i, tested)
    # Forward, a match belongs to the segment of its latest event; backward, to that of its seed, which is no halo.
    halo = F.lit(False) if backward else F.col("is_halo")
    return found.select(*KEY, halo.alias("is_halo"), "t_start", "t_end", "index", "t", *["met"][: int(tested)])


def compact_unordered(found: DataFrame) -> DataFrame:
    """Rows as they come, numbered in no order that means anything; a sort by end is left to the scheduler.

    Room is reserved in two steps: each segment's rows make one block (`rows`), and inside a block a row takes the next place.
    """
    rows = found.select(*KEY, "is_halo", "t_start", F.col("t").alias("t_end"))
    return rows.withColumn("index", F.row_number().over(W.partitionBy(*KEY).orderBy(F.xxhash64("t_start", "t_end"))).cast("long") - 1)


def reservations(found: DataFrame) -> DataFrame:
    """How much room each segment reserves, and where its block begins: the block-level and the global counter."""
    per = found.groupBy(*KEY).agg(F.count("*").alias("rows"))
    before = W.partitionBy("episode_id").orderBy("stream_key", "seg").rowsBetween(W.unboundedPreceding, -1)  # a row for each segment
    return per.withColumn("base", F.coalesce(F.sum("rows").over(before), F.lit(0)))


def compact_padded(found: DataFrame, producers: DataFrame, capacity: int) -> DataFrame:
    """A fixed number of slots for each producer, of which the flagged ones are kept and numbered. Too small a capacity is an error."""
    lists = found.groupBy(*KEY, "index").agg(F.array_sort(F.collect_list(F.struct("t", "is_halo"))).alias("l"))
    checked = F.when(F.size("l") > capacity, F.raise_error(F.lit("capacity exceeded")).cast("array<struct<t:bigint,is_halo:boolean>>")).otherwise(F.col("l"))
    padded = producers.select(*KEY, "t_start", "index").join(lists.select(*KEY, "index", checked.alias("l")), [*KEY, "index"], "left")
    slots = F.transform(F.sequence(F.lit(0), F.lit(capacity - 1)), lambda i: F.get("l", i))
    slotted = padded.select(*KEY, "t_start", "index", F.posexplode(slots).alias("slot", "x")).withColumn("flag", F.col("x").isNotNull().cast("long"))
    # Flags are summed up to each slot, a segment at a time: the place of a used one.
    w = W.partitionBy(*KEY).orderBy("index", "slot").rowsBetween(W.unboundedPreceding, -1)
    placed = slotted.withColumn("place", F.coalesce(F.sum("flag").over(w), F.lit(0)))
    return placed.filter("flag = 1").select(*KEY, F.col("x.is_halo").alias("is_halo"), "t_start", F.col("x.t").alias("t_end"), F.col("place").alias("index"))


def exclusive_scan(df: DataFrame, order: list[str], value: str, op: str = "sum", parts: int | None = None) -> DataFrame:
    """df with `scan`: the operation over all values before the row's, in two levels and without a window over all rows.

    op: sum, max or min; before the first row it is 0 or null.
    """
    spark = df.sparkSession
    n = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    placed = written(df.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()), "scan")
    f = {"sum": F.sum, "max": F.max, "min": F.min}[op]
    # One row for each partition: the only window without a key, over at most n rows.
    totals = placed.groupBy("_part").agg(f(value).alias("_x"))
    offsets = totals.select("_part", f("_x").over(W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)).alias("_before"))
    local = f(value).over(W.partitionBy("_part").orderBy(*order).rowsBetween(W.unboundedPreceding, -1))
    both = placed.withColumn("_local", local).join(F.broadcast(offsets), "_part")
    if op == "sum":
        scan = F.coalesce("_local", F.lit(0)) + F.coalesce("_before", F.lit(0))
    else:
        scan = (F.greatest if op == "max" else F.least)("_local", "_before")
    return both.withColumn("scan", scan).drop("_part", "_local", "_before")


def compact_flags(df: DataFrame, order: list[str], flag: str) -> DataFrame:
    """The flagged rows with their places 0, 1, ... in `index`."""
    return exclusive_scan(df, order, flag).filter(F.col(flag) == 1).withColumnRenamed("scan", "index")


def compact_count_scan_write(producers: DataFrame, match: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Counts for each producer, scans the counts of a segment, then finds again and writes at offset + place: dense and in the producers' order.

    match(producers) finds the next events t; it runs twice, as the method asks for. `index` counts from 0 in each segment.
    """
    counts = match(producers).groupBy(*KEY, "index").agg(F.count("*").alias("cnt"))
    before = W.partitionBy(*KEY).orderBy("index").rowsBetween(W.unboundedPreceding, -1)
    offsets = counts.select(*KEY, "index", F.coalesce(F.sum("cnt").over(before), F.lit(0)).alias("offset"))
    again = match(producers).withColumn("_k", F.row_number().over(W.partitionBy(*KEY, "index").orderBy("t")) - 1)
    placed = again.join(offsets, [*KEY, "index"])
    return placed.select(*KEY, "is_halo", "t_start", F.col("t").alias("t_end"), (F.col("offset") + F.col("_k")).alias("index"))


def track_by(ev: DataFrame, episode: Episode, way: str, capacity: int = 64, seg_len: int | None = None, backward: bool = False) -> DataFrame:
    """All matches of an episode, a row for each path, compacted between levels in one of the ways: unordered, padded, count_scan_write.

    `index` is the place in the segment's dense list: by end for backward count_scan_write, with no sort of the matches; by start
    for the other ordered ones; arbitrary for unordered. Forward, halo rows hold places too.
    """
    cur = seeds(ev, episode, seg_len, backward)
    for i in range(1, len(episode)):
        match = lambda c, i=i: level(c, ev, episode, i, seg_len, backward)
        if way == "unordered":
            cur = compact_unordered(match(cur))
        elif way == "padded":
            cur = compact_padded(match(cur), cur, capacity)
        else:
            cur = compact_count_scan_write(cur, match)
    if backward:
        cur = cur.select(*KEY, "is_halo", (-F.col("t_end")).alias("t_start"), (-F.col("t_start")).alias("t_end"), "index")
    return cur.filter("not is_halo").select(*KEY, "t_start", "t_end", "index")


def dense(found: DataFrame) -> DataFrame:
    """`index` over all segments of an episode: each segment's places after those of the segments before it."""
    bases = reservations(found)
    return found.join(F.broadcast(bases.select(*KEY, "base")), KEY).withColumn("index", F.col("base") + F.col("index")).drop("base")
