"""The paper's experiments on the given tables: every method on every step, so that counts and run times can be compared."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .catalog import BANDS, CYCLE, DAY, EVENTS, MAIN, NEURONS, THIRTY, U, add, by_step, counter, gapped, one, prefix, sql_count, sql_levels, sql_paths, u, union
from .functions.model import Episode
from .operators import counting, measures, mining, segments, serial, stitching
from .operators.segments import WAYS
from .sources import streams as S

COUNTERS = ("serial", "episode_parallel", "segment_machines", "segment_exact", "local_tracking")
LENGTH = [(n, lo, hi) for n in range(1, 10) for lo, hi in ((0, 6), (5, 10))]
WIDTHS = (1, 2, 4, 8, 16, 32, 64)
RARE = {
    "type": ("view>click>purchase", CYCLE[:3], EVENTS, S.events_by_type),
    "band": ("view_0>click_0>purchase_0", ["view_0", "click_0", "purchase_0"], BANDS, S.events_by_type_bucket),
    "neuron": ("n00>n01>n02", ["n00", "n01", "n02"], NEURONS, S.events_by_neuron),
}
NEURON_EP = [[f"n{a + i:02d}" for i in range(3)] for a in range(0, 64, 8)]


def wide(parts: list[tuple[str, str]]) -> str:
    return union([f"SELECT {cols}, n FROM ({q})" for cols, q in parts])


def thirty(unit: int) -> list[Episode]:
    return [gapped(p, 5, 10, unit) for p in THIRTY]


def ladder(spark: SparkSession, d: str) -> DataFrame:
    """All eight prefixes of `events` as streams of one table; instants are read as sets, so that nothing has to be merged first."""
    return S.ladder_streams(S.events_by_type(spark, d, merge=False))


def count_by(method: str, ev: DataFrame, episodes: list[Episode], unit: int) -> DataFrame:
    """The counters that the paper compares, on the same stream and segments of 200 units."""
    return {
        "serial": lambda: serial.count_serial(ev, episodes, evict=True),
        "episode_parallel": lambda: serial.count_episode_parallel(ev, episodes),
        "segment_machines": lambda: stitching.count_segment_machines(ev, episodes, 200 * unit),
        "segment_exact": lambda: stitching.count_segment_exact(ev, episodes, 200 * unit),
        "local_tracking": lambda: counting.count_nonoverlapping(ev, episodes, seg_len=200 * unit),
    }[method]()


def every_counter(spark: SparkSession, d: str, episodes: list[Episode], methods: tuple[str, ...]) -> DataFrame:
    ev, unit = ladder(spark, d), S.unit(spark, d)
    return by_step(reduce(DataFrame.unionByName, [count_by(m, ev, episodes, unit).withColumn("method", F.lit(m)) for m in methods]))


# W1: thirty episodes on the eight prefixes
STEP_SQL = wide([(f"{a} AS num, {b} AS den, episode_id", union([sql_count(">".join(p), p, [u(5, 10)] * 2, prefix(EVENTS, a, b)) for p in THIRTY])) for a, b in S.LADDER])
add("w1_thirty_episodes", union([sql_count(">".join(p), p, [u(5, 10)] * 2) for p in THIRTY]))(lambda spark, d: serial.count_episode_parallel(S.events_by_type(spark, d), thirty(S.unit(spark, d))))
add("w1_ladder", STEP_SQL)(
    lambda spark, d: every_counter(spark, d, thirty(S.unit(spark, d)), ("local_tracking",)).drop("method")
)


@add("w1_methods")  # 240 counts by each of five counters; equal to the serial one in tests, and one of them to SQL in w1_ladder
def w1_methods(spark: SparkSession, d: str) -> DataFrame:
    return every_counter(spark, d, thirty(S.unit(spark, d)), COUNTERS)


# W2: the profile on half the time span
HALF = prefix(EVENTS, 1, 2)


def sql_tests(source: str) -> str:
    """Forward tests of each level by definition: for each path the events after it up to the first beyond the bound."""
    (_, types, gaps), parts = MAIN, []
    for i in (1, 2):
        reach = f"WITH {sql_levels(types[:i], gaps[: i - 1], source, False)} SELECT x.f, count(e.t) + 1 AS c, count(CASE WHEN e.t > x.f + {gaps[i - 1][0]} THEN 1 END) AS m FROM (SELECT *, row_number() OVER () AS id FROM l{i - 1}) x LEFT JOIN e ON e.ty = '{types[i]}' AND e.t > x.f AND e.t <= x.f + {gaps[i - 1][1]} GROUP BY x.id, x.f"
        parts.append(f"SELECT {i} AS level, count(*) AS producers, CAST(sum(c) AS BIGINT) AS tests, CAST(sum(m) AS BIGINT) AS matches FROM ({reach})")
    return union(parts)


add("w2_profile", f"SELECT level, producers, matches, w AS way, CASE WHEN w = 'count_scan_write' THEN 2 ELSE 1 END * tests AS tests FROM ({sql_tests(HALF)}), (VALUES ('unordered'), ('padded'), ('count_scan_write')) v(w)")(
    # One segment, as a halo is searched again in the next one.
    lambda spark, d: segments.level_costs(S.ladder_prefix(S.events_by_type(spark, d), (1, 2)), one(S.unit(spark, d)), 2 * S.ORIGIN, WAYS[:3]).filter("matches > 0").select("level", "producers", "matches", "way", "tests")
)


@add("w2_machines")  # counted while the machines run; SQL cannot run them
def w2_machines(spark: SparkSession, d: str) -> DataFrame:
    """instructions, branches and divergent groups of the segment machines and of each way, on the second dataset of the ladder."""
    unit = S.unit(spark, d)
    return measures.profile(S.ladder_prefix(S.events_by_type(spark, d), (1, 2)), one(unit)[0], 200 * unit)


# W3: one episode on the eight prefixes
W3_SQL = wide([(f"{a} AS num, {b} AS den, episode_id", sql_count(*MAIN, prefix(EVENTS, a, b))) for a, b in S.LADDER])
add("w3_ladder", W3_SQL)(lambda spark, d: every_counter(spark, d, one(S.unit(spark, d)), ("local_tracking",)).drop("method"))
add("w3_methods", f"SELECT num, den, episode_id, n, m AS method FROM ({W3_SQL}), (VALUES {', '.join(f"('{m}')" for m in COUNTERS)}) v(m)")(lambda spark, d: every_counter(spark, d, one(S.unit(spark, d)), COUNTERS))


# W4: length of the episode, and W5: its frequency, by each way of compaction
def cycle(n: int) -> list[str]:
    return [CYCLE[i % 5] for i in range(n)]


def lengths(unit: int) -> list[Episode]:
    return [Episode.of(*cycle(n), gaps=[(lo * unit, hi * unit)] * (n - 1), episode_id=f"{n}:{lo}:{hi}") for n, lo, hi in LENGTH]


def widths(unit: int) -> list[Episode]:
    return [Episode.of(*CYCLE[:3], gaps=[(0, h * unit)] * 2, episode_id=str(h)) for h in WIDTHS]


def with_paths(name: str, types: list[str], gaps: list[tuple[str, str]], source: str = EVENTS) -> str:
    return f"SELECT c.episode_id, n, paths FROM ({sql_count(name, types, gaps, source)}) c JOIN ({sql_paths(name, types, gaps, source)}) p USING (episode_id)"


def each_way(sql: str) -> str:
    return f"SELECT x.*, w AS way FROM ({sql}) x, (VALUES {', '.join(f"('{w}')" for w in WAYS)}) v(w)"


LENGTH_SQL = union([with_paths(f"{n}:{lo}:{hi}", cycle(n), [u(lo, hi)] * (n - 1)) for n, lo, hi in LENGTH])
WIDTH_SQL = union([with_paths(str(h), MAIN[1], [u(0, h)] * 2) for h in WIDTHS])
counter("w4_length", union([sql_count(f"{n}:{lo}:{hi}", cycle(n), [u(lo, hi)] * (n - 1)) for n, lo, hi in LENGTH]), lambda ev, ep, unit: counting.count_nonoverlapping(ev, ep), lengths)
counter("w4_length_ways", each_way(LENGTH_SQL), lambda ev, ep, unit: segments.count_compacted(ev, ep, 1000 * unit).drop("stream_key"), lengths)
counter("w5_width", f"SELECT CAST(episode_id AS INT) AS width, paths, n FROM ({WIDTH_SQL})",
        lambda ev, ep, unit: counting.count_nonoverlapping(ev, ep).join(measures.count_overlapped(ev, ep), "episode_id").select(F.col("episode_id").cast("int").alias("width"), "paths", "n"), widths)
counter("w5_width_ways", each_way(WIDTH_SQL), lambda ev, ep, unit: segments.count_compacted(ev, ep, 2000 * unit).drop("stream_key"), widths)
RARITY_SQL = union([f"SELECT '{k}' AS symbols, n, paths FROM ({with_paths(name, types, [u(0, 64)] * 2, source)})" for k, (name, types, source, _) in RARE.items()])


def rarity(spark: SparkSession, d: str, f) -> DataFrame:
    unit = S.unit(spark, d)
    return reduce(DataFrame.unionByName, [f(source(spark, d), [gapped(types, 0, 64, unit)], unit).withColumn("symbols", F.lit(k)) for k, (_, types, _, source) in RARE.items()])


add("w5_rarity", RARITY_SQL)(
    lambda spark, d: rarity(spark, d, lambda ev, ep, unit: counting.count_nonoverlapping(ev, ep).join(measures.count_overlapped(ev, ep), "episode_id", "left").select("n", F.coalesce("paths", F.lit(0)).alias("paths")))
)
add("w5_rarity_ways", each_way(RARITY_SQL))(lambda spark, d: rarity(spark, d, lambda ev, ep, unit: segments.count_compacted(ev, ep, 2000 * unit).select("n", "paths", "way")))


# W7: the network of 64 neurons
def neurons(spark: SparkSession, d: str) -> DataFrame:
    ev, ep = S.events_by_neuron(spark, d), [Episode.of(*p, gaps=[(0, DAY // 2)] * 2) for p in NEURON_EP]
    return counting.count_nonoverlapping(ev, ep).join(measures.count_overlapped(ev, ep), "episode_id", "left").select("episode_id", "stream_key", "n", F.coalesce("paths", F.lit(0)).alias("paths"))


add("w7_neurons", union([f"SELECT c.episode_id, stream_key, n, paths FROM ({sql_count('>'.join(p), p, [('0', str(DAY // 2))] * 2, NEURONS)}) c JOIN ({sql_paths('>'.join(p), p, [('0', str(DAY // 2))] * 2, NEURONS)}) q USING (episode_id)" for p in NEURON_EP]))(neurons)


# Chains planted into the network that `events` gives, in its units of time
LATER = "coalesce(list_sum(list_transform(range(1, i + 1), lambda j: 6 + (x + j) % 5)), 0)"
FIRED = ", ".join(f"({c}, {i}, '{n}')" for c, chain in enumerate(S.CHAINS) for i, n in enumerate(chain))
PLANTED = f"(SELECT * FROM {NEURONS} UNION SELECT 'all', ty, CAST(s.t + {LATER} * {U} AS BIGINT) FROM (SELECT event_id // {S.CHAIN_EVERY} AS x, epoch_us(ts) AS t FROM events WHERE event_id % {S.CHAIN_EVERY} = 0) s JOIN (VALUES {FIRED}) v(c, i, ty) ON c = x % {len(S.CHAINS)})"


@add("w7_generator", union([sql_count(">".join(c), c, [u(5, 10)] * (len(c) - 1), PLANTED) for c in S.CHAINS]))
def w7_generator(spark: SparkSession, d: str) -> DataFrame:
    unit = S.unit(spark, d)
    return counting.count_nonoverlapping(S.planted(spark, d, unit), [gapped(c, 5, 10, unit) for c in S.CHAINS])


def mine_planted(spark: SparkSession, seconds: int) -> tuple[list[tuple[str, ...]], list[list[str]]]:
    """Level-wise mining of a generated stream, and the chains that were planted: the nine-node episodes found, and the truth.

    Noise of 20 spikes a second meets a gap (5,10] by chance in a tenth of the cases; a chain that fires eight times a
    second stands out from the second level on. The threshold grows with the length of the stream.
    """
    ev, chains = S.spikes(spark, seconds=seconds, rate=20.0, firings=8.0)
    found = mining.mine(ev, [(5, 10)], 4 * seconds, max_level=9, counter="tracking")
    return [e.types for level, e, _ in found if level == 9], chains


@add("w7_mined")
def w7_mined(spark: SparkSession, d: str) -> DataFrame:
    found, chains = mine_planted(spark, 20)
    return spark.createDataFrame([(">".join(c), tuple(c) in set(found), len(found)) for c in chains], "chain string, found boolean, nine_node_episodes int")


# W11: phrases of the benchmark in the texts of documents
PHRASE_WORDS = 5


@add("count_phrases")  # compared with a search by hand in tests: greedy picks leave out overlapping repeats, which SQL joins count
def count_phrases(spark: SparkSession, d: str) -> DataFrame:
    """How often the first five words of each benchmark item stand side by side in a document, without overlap; documents that have none are left out."""
    phrases = sorted(set(S.benchmark_passages(spark, d, PHRASE_WORDS)))
    episodes = [Episode.of(*p, gaps=[(0, 1)] * (PHRASE_WORDS - 1), episode_id=" ".join(p)) for p in phrases]
    if not episodes:
        return spark.createDataFrame([], "phrase string, documents long, n long")
    counts = segments.count_segments(S.document_tokens(spark, d), episodes, 1 << 40)
    return counts.filter("n > 0").groupBy(F.col("episode_id").alias("phrase")).agg(F.count("*").alias("documents"), F.sum("n").alias("n"))
