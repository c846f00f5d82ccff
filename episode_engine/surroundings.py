"""Scans, sinks, SQL entry and relational operators around the methods that have a query of their own."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .catalog import CYCLE, DAY, EVENTS, MAIN_SQL, OCC_SQL, U, add, labelled, main, mined, one, relational, sql_mine, union
from .functions.model import Episode
from .operators import counting, serial, tracking
from .plans.storage import shared_place
from .sources import streams as S
from .streaming import online

FORMATS = {"csv": "event_id long, event_type string, ticks long", "json": "event_id long, event_type string, ticks long", "orc": None, "parquet": None}


# S2-S4: what reaches the scan
@add("scan_pushdown", "SELECT event_type, epoch_us(ts) AS t FROM events WHERE event_type IN ('view', 'click')")
def scan_pushdown(spark: SparkSession, d: str) -> DataFrame:
    """Types are filtered on the raw column, so that the filter reaches the Parquet reader."""
    return S.table(spark, d, "events").filter(F.col("event_type").isin("view", "click")).select("event_type", S.micros(F.col("ts")).alias("t"))


@add("scan_time_range", "SELECT event_type, epoch_us(ts) AS t FROM events WHERE ts >= TIMESTAMP '2024-01-10' AND ts < TIMESTAMP '2024-01-12'")
def scan_time_range(spark: SparkSession, d: str) -> DataFrame:
    """A time range on the raw timestamp: a computed tick would not be pushed."""
    raw = S.table(spark, d, "events")
    kind = raw.schema["ts"].dataType.simpleString()
    low, high = (F.lit(x).cast(kind) for x in ("2024-01-10 00:00:00", "2024-01-12 00:00:00"))
    return raw.filter((F.col("ts") >= low) & (F.col("ts") < high)).select("event_type", S.micros(F.col("ts")).alias("t"))


@add("scan_segment", f"SELECT ty AS event_type, t FROM {EVENTS} WHERE t // {DAY} = {S.ORIGIN // DAY + 3}")
def scan_segment(spark: SparkSession, d: str) -> DataFrame:
    """A layout by segment on disk: a read of one segment opens its folder only."""
    place = f"{shared_place(spark)}/by-segment-{abs(hash(d))}"
    S.events_by_type(spark, d).withColumn("seg", S.floor_div(F.col("t"), DAY)).repartition("seg").write.mode("overwrite").partitionBy("seg").parquet(place)
    return spark.read.parquet(place).filter(F.col("seg") == S.ORIGIN // DAY + 3).select("event_type", "t")


# S5, S6: formats and sinks
def through_format(events: DataFrame, kind: str, place: str) -> DataFrame:
    events.write.mode("overwrite").format(kind).save(place)
    reader = events.sparkSession.read.format(kind)
    return (reader.schema(FORMATS[kind]) if FORMATS[kind] else reader).load(place)


@add("sink_formats", union([f"SELECT '{k}' AS kind, event_id, event_type, epoch_us(ts) AS ticks FROM events" for k in FORMATS]))
def sink_formats(spark: SparkSession, d: str) -> DataFrame:
    rows = S.table(spark, d, "events").select("event_id", "event_type", S.micros(F.col("ts")).alias("ticks"))
    out = None
    for k in FORMATS:
        part = through_format(rows, k, f"{shared_place(spark)}/as-{k}-{abs(hash(d))}").select(F.lit(k).alias("kind"), "event_id", "event_type", "ticks")
        out = part if out is None else out.unionByName(part)
    return out


@add("sink_occurrences", OCC_SQL)
def sink_occurrences(spark: SparkSession, d: str) -> DataFrame:
    """Occurrences as Parquet by episode, in order of their ends inside a file, and read again."""
    ev, ep, unit = main(spark, d)
    place = f"{shared_place(spark)}/occurrences-{abs(hash(d))}"
    tracking.track_window_asof(ev, ep, 200 * unit).repartition("episode_id", "seg").sortWithinPartitions("t_end").write.mode("overwrite").partitionBy("episode_id").parquet(place)
    return spark.read.parquet(place).select("t_start", "t_end")


# S7 and user-defined functions
class EpisodeOccurrences:
    """A table function over the rows of one stream: the occurrences that greedy by end picks."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, str]] = []
        self.text = ""

    def eval(self, text: str, row) -> None:
        self.text = text
        self.rows.append((row["t"], row["event_type"]))

    def terminate(self) -> Iterator[tuple]:
        if self.rows:
            yield from chosen(Episode.parse(self.text), sorted(self.rows))


def chosen(e: Episode, rows: list[tuple[int, str]]) -> Iterator[tuple[int, int]]:
    times = [np.unique([t for t, ty in rows if ty == x]).astype(np.int64) for x in e.types]
    start, end = tracking.best_starts(times, e.low, e.high)
    last = None
    for a, b in zip(start.tolist(), end.tolist(), strict=True):
        if last is None or a > last:
            last = b
            yield a, b


def register(spark: SparkSession) -> None:
    """`episode_occurrences(episode, TABLE(...))` and `count_episode(event_type, t, episode)` for SQL. Both read one group whole: partition by a key that fits a task."""
    spark.udtf.register("episode_occurrences", F.udtf(EpisodeOccurrences, returnType="t_start bigint, t_end bigint"))

    @F.pandas_udf("bigint")
    def count_episode(ty: pd.Series, t: pd.Series, text: pd.Series) -> int:
        return serial.count_instants(Episode.parse(text.iat[0]), serial.instants(t.tolist(), ty.tolist()), True) if len(t) else 0

    spark.udf.register("count_episode", count_episode)


def as_text(unit: int) -> str:
    return f"view -({5 * unit},{10 * unit}]-> click -({5 * unit},{10 * unit}]-> purchase"


CHOSEN = f"""WITH RECURSIVE o AS ({OCC_SQL}), g AS (SELECT min(t_end) AS f FROM o UNION ALL SELECT (SELECT min(t_end) FROM o WHERE t_start > g.f) FROM g WHERE EXISTS (SELECT 1 FROM o WHERE t_start > g.f))
 SELECT o.t_start, g.f AS t_end FROM g JOIN o ON o.t_end = g.f"""


@add("udtf_occurrences", CHOSEN)
def udtf_occurrences(spark: SparkSession, d: str) -> DataFrame:
    register(spark)
    ev = S.events_by_type(spark, d).filter(F.col("event_type").isin(*CYCLE[:3]))
    return spark.sql("SELECT t_start, t_end FROM episode_occurrences(:text, TABLE({ev}) PARTITION BY stream_key ORDER BY t)", args={"text": as_text(S.unit(spark, d))}, ev=ev)


@add("sql_entry", f"SELECT stream_key, n FROM ({MAIN_SQL})")
def sql_entry(spark: SparkSession, d: str) -> DataFrame:
    """The count as an aggregate function of SQL over a view."""
    register(spark)
    S.events_by_type(spark, d).createOrReplaceTempView("event_stream")
    return spark.sql("SELECT stream_key, count_episode(event_type, t, :text) AS n FROM event_stream GROUP BY stream_key", args={"text": as_text(S.unit(spark, d))})


# Relational operators
@add("join_theta", f"WITH e AS (SELECT * FROM {EVENTS}) SELECT a.t AS t_start, b.t AS t_end FROM e a JOIN e b ON a.ty = 'purchase' AND b.ty = 'signup' AND a.t < {S.ORIGIN + 3 * DAY} AND b.t > a.t + 5 * {U} AND b.t <= a.t + 10 * {U}")
def join_theta(spark: SparkSession, d: str) -> DataFrame:
    """The gap as a bare condition: a nested loop, the reference for the bucketed join. Its left side is three days, its cost the product."""
    unit, ev = S.unit(spark, d), S.events_by_type(spark, d)
    a = ev.filter((F.col("event_type") == "purchase") & (F.col("t") < S.ORIGIN + 3 * DAY)).select(F.col("t").alias("t_start"))
    b = ev.filter("event_type = 'signup'").select(F.col("t").alias("t_end"))
    return a.join(b, (F.col("t_end") > F.col("t_start") + 5 * unit) & (F.col("t_end") <= F.col("t_start") + 10 * unit))


@add("topk_episodes", f"SELECT level, types, n FROM (SELECT *, row_number() OVER (PARTITION BY level ORDER BY n DESC, types) AS r FROM ({sql_mine(3)})) WHERE r <= 5")
def topk_episodes(spark: SparkSession, d: str) -> DataFrame:
    """The five most frequent episodes of each level: a report, and a limit by intent."""
    return _top(labelled(spark, mined(spark, d, [(5, 10)])))


def _top(found: DataFrame) -> DataFrame:
    place = F.row_number().over(W.partitionBy("level").orderBy(F.desc("n"), "types"))
    return found.withColumn("_r", place).filter("_r <= 5").drop("_r")


GAPS = "(SELECT event_type, epoch_us(ts) // 1000000 - epoch_us(lag(ts) OVER (PARTITION BY event_type ORDER BY ts)) // 1000000 AS gap FROM events)"
SPARK_GAPS = "(SELECT event_type, unix_seconds(CAST(ts AS TIMESTAMP)) - unix_seconds(CAST(lag(ts) OVER (PARTITION BY event_type ORDER BY ts) AS TIMESTAMP)) AS gap FROM {events})"
relational("agg_gap_quantiles", f"SELECT event_type, round(percentile(gap, 0.5), 3) AS median, round(percentile(gap, 0.9), 3) AS p90 FROM {SPARK_GAPS} WHERE gap IS NOT NULL GROUP BY event_type",
           f"SELECT event_type, round(quantile_cont(gap, 0.5), 3) AS median, round(quantile_cont(gap, 0.9), 3) AS p90 FROM {GAPS} WHERE gap IS NOT NULL GROUP BY event_type")
relational("agg_gap_histogram", f"SELECT event_type, least(gap DIV 600, 20) AS bucket, count(*) AS n FROM {SPARK_GAPS} WHERE gap IS NOT NULL GROUP BY 1, 2",
           f"SELECT event_type, least(gap // 600, 20) AS bucket, count(*) AS n FROM {GAPS} WHERE gap IS NOT NULL GROUP BY 1, 2")
relational("window_tiles", "SELECT event_id, ntile(4) OVER (PARTITION BY event_type ORDER BY event_id) AS tile, round(percent_rank() OVER (PARTITION BY event_type ORDER BY event_id), 9) AS pr FROM {events}")
relational("window_values", "SELECT event_id, first_value(event_id) OVER w AS f, last_value(event_id) OVER w AS l, nth_value(event_id, 2) OVER w AS s FROM {events} WINDOW w AS (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW)")
relational("window_rows", "SELECT event_id, sum(user_id) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS s FROM {events}", "SELECT event_id, CAST(sum(user_id) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS s FROM events")
relational("fn_array", "SELECT user_id, array_join(slice(array_sort(collect_set(event_type)), 1, 3), ',') AS types, CAST(aggregate(transform(filter(array_sort(collect_list(event_id)), x -> x % 2 = 0), x -> x % 10), 0L, (a, x) -> a + x) AS BIGINT) AS s FROM {events} GROUP BY user_id",
           "SELECT user_id, array_to_string(list_sort(list_distinct(list(event_type)))[1:3], ',') AS types, CAST(coalesce(list_sum(list_transform(list_filter(list(event_id), lambda x: x % 2 = 0), lambda x: x % 10)), 0) AS BIGINT) AS s FROM events GROUP BY user_id")
relational("fn_map", "SELECT user_id, m['view'] AS views, array_join(array_sort(map_keys(m)), ',') AS types FROM (SELECT user_id, map_from_entries(collect_list(struct(event_type, n))) AS m FROM (SELECT user_id, event_type, count(*) AS n FROM {events} GROUP BY user_id, event_type) GROUP BY user_id)",
           "SELECT user_id, max(CASE WHEN event_type = 'view' THEN n END) AS views, string_agg(event_type, ',' ORDER BY event_type) AS types FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) GROUP BY user_id")
add("agg_approx")(lambda spark, d: S.table(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users")))  # a sketch: other engines' sketches differ
for _name, _source, _sql in (
    ("stream_per_supplier", S.lineitem_per_supplier, "SELECT CAST(l_suppkey AS VARCHAR) AS stream_key, r_name || '_' || l_returnflag AS event_type, epoch_us(l_shipdate) AS t, count(*) AS mult FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL"),
    ("stream_part_types", S.part_types, "SELECT 'all' AS stream_key, p_brand AS event_type, epoch_us(l_shipdate) AS t, count(*) AS mult FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL"),
):
    add(_name, _sql)(_source)


@add("sample_segments")
def sample_segments(spark: SparkSession, d: str, share: float = 0.25) -> DataFrame:
    """Whole days drawn by a hash, counted, and scaled to all days: an estimate beside the exact count. A sampling operator, so that it reads a part by intent."""
    ev, ep, unit = main(spark, d)
    day = S.floor_div(F.col("t"), DAY)
    drawn = ev.withColumn("stream_key", F.concat_ws("@", "stream_key", day)).filter(F.pmod(F.xxhash64(day), F.lit(1000)) < int(1000 * share))
    days, some = (x.select(day.alias("x")).distinct().count() for x in (ev, ev.filter(F.pmod(F.xxhash64(day), F.lit(1000)) < int(1000 * share))))
    n = counting.count_nonoverlapping(drawn, ep).groupBy("episode_id").agg(F.sum("n").alias("sampled"))
    exact = counting.count_nonoverlapping(ev, ep).groupBy("episode_id").agg(F.sum("n").alias("exact"))
    return n.join(exact, "episode_id").withColumn("estimate", F.round(F.col("sampled") * days / max(some, 1), 1))


@add("sample_types", None)
def sample_types(spark: SparkSession, d: str) -> DataFrame:
    """A stratified sample by type: a sampling operator."""
    return S.table(spark, d, "events").sampleBy("event_type", {t: 0.1 for t in CYCLE}, seed=7).groupBy("event_type").agg(F.count("*").alias("n"))


# T4: windows counted apart, and how far they may be off
@add("stream_window_bound", f"SELECT episode_id, TRUE AS holds FROM ({MAIN_SQL})")
def stream_window_bound(spark: SparkSession, d: str) -> DataFrame:
    """Counts of one-day windows against the exact one: 0 <= exact - approximate <= borders, as a border is crossed by one of a disjoint set at most."""
    unit = S.unit(spark, d)
    batches = online.run_available(online.online_count(online.tumbling_keys(online.events_stream(spark, d), DAY), one(unit), "1 day"), "update")
    last = batches.groupBy("episode_id", "stream_key").agg(F.max("n").alias("n"))
    approx = last.groupBy("episode_id").agg(F.sum("n").alias("approx"))
    exact = counting.count_nonoverlapping(S.events_by_type(spark, d), one(unit), seg_len=200 * unit).groupBy("episode_id").agg(F.sum("n").alias("exact"))
    off = F.col("exact") - F.coalesce("approx", F.lit(0))
    return exact.join(approx, "episode_id", "left").select("episode_id", ((off >= 0) & (off <= S.DAYS - 1)).alias("holds"))
