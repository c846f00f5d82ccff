"""Counts over unbounded streams: an online serial counter, windowed counts, and one level of tracking as a join of streams."""

from __future__ import annotations

import json
import uuid
from collections import deque
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.model import Episode, episode_nodes, gap_ok
from ..operators.serial import Machine, instants
from ..plans.storage import shared_place
from ..sources.streams import floor_div, micros

ONLINE = "episode_id string, stream_key string, n long, settled long, late long, held long"


def events_stream(spark: SparkSession, sf_dir: str, files_per_batch: int | None = None) -> DataFrame:
    """`events` as a stream of stream_key, event_id, event_type, t and event_time."""
    path = f"{sf_dir}/events.parquet"
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    t = micros(F.col("ts"))
    # A stream takes a table of one file only by a pattern.
    rows = reader.parquet(f"{sf_dir}/events.parque[t]").filter("event_type is not null and ts is not null")
    return rows.select(F.lit("all").alias("stream_key"), "event_id", "event_type", t.alias("t"), F.timestamp_micros(t).alias("event_time"))


def tumbling_keys(stream: DataFrame, width: int) -> DataFrame:
    """Each window of `width` microseconds as a stream of its own: occurrences across a border are missed."""
    return stream.withColumn("stream_key", F.concat_ws("@", "stream_key", F.floor(F.col("t") / width).cast("string")))


def _load(raw: str | None, e: Episode) -> tuple[Machine, list, int, int]:
    m = Machine(e, evict=True)
    if raw is None:
        return m, [], -(1 << 62), 0
    got = json.loads(raw)
    m.n, m.last, m.lists = got["n"], got["last"], [deque(x) for x in got["lists"]]
    return m, got["waiting"], got["front"], got["late"]


def feed(m: Machine, rows: list) -> None:
    for t, types in instants([t for t, _ in rows], [ty for _, ty in rows]):
        m.feed(t, types)


def online_count(stream: DataFrame, episodes: list[Episode], delay: str) -> DataFrame:
    """stream(stream_key, event_type, t, event_time) -> ONLINE, in update mode: a row for each stream and episode with news.

    Events wait until the watermark (the latest event_time less `delay`) has passed them, and are then fed to the serial counter in order
    of time; `settled` counts these alone, `n` also the `held` ones that wait. Both only grow. An event behind what was fed is dropped;
    `late` counts those that Spark has not dropped itself. State is what waits and, of bounded gaps, what is within reach.
    A null type or time is no event; an empty stream gives no rows.
    """
    by_id = {e.episode_id: e for e in episodes}

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        m, waiting, front, late = _load(state.get[0] if state.exists else None, by_id[key[0]])
        for b in batches:
            for t, ty in zip(b["t"].tolist(), b["event_type"].tolist(), strict=True):
                if t < front:
                    late += 1
                else:
                    waiting.append([t, ty])
        mark = state.getCurrentWatermarkMs()  # 0 before the first
        passed = max(front, 1000 * mark) if mark > 0 else front
        feed(m, [w for w in waiting if w[0] < passed])
        waiting = sorted({(t, ty) for t, ty in waiting if t >= passed})
        kept = json.dumps({"n": m.n, "last": m.last, "lists": [list(x) for x in m.lists], "waiting": waiting, "front": passed, "late": late})
        state.update((kept,))
        if waiting:  # settles in time even where no event of this stream follows
            state.setTimeoutTimestamp(max(waiting[-1][0] // 1000 + 1, mark + 1))
        settled = m.n
        feed(m, waiting)
        yield pd.DataFrame({"episode_id": [key[0]], "stream_key": [key[1]], "n": [m.n], "settled": [settled], "late": [late], "held": [len(waiting)]})

    # The few types of each episode are broadcast.
    wanted = F.broadcast(episode_nodes(stream.sparkSession, episodes).select("episode_id", "event_type").distinct())
    rows = stream.withWatermark("event_time", delay).join(wanted, "event_type").select("episode_id", "stream_key", "event_type", "t", "event_time")
    return rows.groupBy("episode_id", "stream_key").applyInPandasWithState(step, ONLINE, "state string", "update", GroupStateTimeout.EventTimeTimeout)


def type_counts(stream: DataFrame, delay: str, width: str, slide: str | None = None) -> DataFrame:
    """Events of each type in tumbling or sliding windows."""
    w = F.window("event_time", width, slide)
    return stream.withWatermark("event_time", delay).groupBy(w, "event_type").agg(F.count("*").alias("n")).select("event_type", F.unix_micros("window.start").alias("start"), "n")


def session_counts(stream: DataFrame, delay: str, gap: str) -> DataFrame:
    """Events of each type in sessions that a silence of `gap` ends."""
    w = F.session_window("event_time", gap)
    return stream.withWatermark("event_time", delay).groupBy(w, "event_type").agg(F.count("*").alias("n")).select("event_type", F.unix_micros("session_window.start").alias("start"), "n")


def first_seen(stream: DataFrame, delay: str, key: str = "event_id") -> DataFrame:
    """Each key once, for as long as the watermark lets it be repeated."""
    return stream.withWatermark("event_time", delay).dropDuplicatesWithinWatermark([key])


def interval_join(left: DataFrame, right: DataFrame, first: str, second: str, low: int, high: int, delay: str) -> DataFrame:
    """One level of tracking between two streams: starts and ends of pairs with a gap in (low, high] microseconds.

    Rows meet in buckets of time as wide as the bound, two for each start at most, so that an event is compared with its neighbours only and
    the state of one long stream is dealt to all tasks. An end has one bucket, so that no pair is met twice.
    """
    width = max(high, 1)
    reached = F.sequence(floor_div(F.col("t_start") + max(low + 1, 0), width), floor_div(F.col("t_start") + high, width))
    a = left.filter(F.col("event_type") == first).withWatermark("event_time", delay).select(F.col("stream_key").alias("k"), F.col("t").alias("t_start"), F.col("event_time").alias("a_time")).withColumn("bucket", F.explode(reached))
    b = right.filter(F.col("event_type") == second).withWatermark("event_time", delay).select("stream_key", F.col("t").alias("t_end"), F.col("event_time").alias("b_time")).withColumn("meets", floor_div(F.col("t_end"), width))
    within = F.col("b_time").between(F.col("a_time"), F.col("a_time") + F.make_dt_interval(secs=F.lit(high / 1e6)))
    return a.join(b, (F.col("k") == F.col("stream_key")) & (F.col("bucket") == F.col("meets")) & within & gap_ok(F.col("t_end") - F.col("t_start"), low, high)).select("stream_key", "t_start", "t_end")


def run_available(df: DataFrame, mode: str, checkpoint: str | None = None) -> DataFrame:
    """Runs what is there to its end and reads back every batch's rows, with `batch`; the same `checkpoint` goes on where it stopped."""
    spark = df.sparkSession
    place = checkpoint or f"{shared_place(spark)}/stream-{uuid.uuid4().hex}"
    schema = f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in df.schema)}, batch long"

    def put(rows: DataFrame, batch: int) -> None:  # a batch that is run again replaces its own folder
        rows.withColumn("batch", F.lit(batch).cast("long")).write.mode("overwrite").parquet(f"{place}/out/n{batch}")

    spark.createDataFrame([], schema).write.mode("overwrite").parquet(f"{place}/out/none")
    df.writeStream.outputMode(mode).option("checkpointLocation", f"{place}/state").foreachBatch(put).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(f"{place}/out")
