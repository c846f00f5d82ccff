"""Rules that choose how to count, before any DataFrame is built."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def choose_strategy(k: int, nodes: int, events: int, cores: int) -> str:
    """Many short episodes: a worker for each. Few or long ones: all cores on the events of each."""
    return "episodes" if k >= 16 * cores and nodes <= 2 and events < 1_000_000 else "tracking"


def choose_compaction(nodes: int, matches: int) -> str:
    """Short episodes need no sort after count-scan-write; for long ones unordered rows and one sort are cheaper, unless they are very many."""
    return "count_scan_write" if nodes <= 4 or matches > 50_000_000 else "unordered"


def segment_length(halo: int, span: int, events: int, cores: int = 1, per_segment: int = 2_000_000) -> int:
    """At least twenty halos, so that a twentieth of the rows is copied at most; else so long that a segment fits a task, and two come to each core."""
    per_segment = min(per_segment, max(events // (2 * cores), 10_000))
    return max(20 * halo, span * per_segment // max(events, 1), 1)


def default_segment(ev: DataFrame, halo: int) -> int:
    """segment_length for the stream with the most events; one aggregate over the keys and times."""
    per = ev.groupBy("stream_key").agg(F.count("*").alias("n"), (F.max("t") - F.min("t") + 1).alias("span"))
    top = per.agg(F.max(F.struct("n", "span")).alias("x")).first()["x"]
    return segment_length(halo, top["span"], top["n"], ev.sparkSession.sparkContext.defaultParallelism) if top else max(halo, 1)


@dataclass(frozen=True)
class CountPlan:
    """What counting will do, before any DataFrame is built."""

    strategy: str
    compaction: str
    halo: int | None
    seg_len: int | None
    tasks: int
    cores: int

    @property
    def utilisation(self) -> float:
        """Busy cores of all cores while the widest step runs."""
        return min(self.tasks, self.cores) / self.cores


def plan_count(episodes: int, nodes: int, halo: int | None, span: int, events: int, cores: int, matches: int | None = None) -> CountPlan:
    """The rules above together: episodes and their longest length, the halo, and the time span and size of the stream."""
    strategy = choose_strategy(episodes, nodes, events, cores)
    seg_len = None if halo is None or strategy == "episodes" else segment_length(halo, span, events, cores)
    tasks = episodes if seg_len is None else -(-span // seg_len)
    return CountPlan(strategy, choose_compaction(nodes, events if matches is None else matches), halo, seg_len, max(tasks, 1), cores)


def explain(plan: CountPlan, df: DataFrame | None = None) -> str:
    """The CountPlan, and the physical plan of a DataFrame made by it."""
    text = "\n".join(f"{k}: {v}" for k, v in [*plan.__dict__.items(), ("utilisation", round(plan.utilisation, 3))])
    return text if df is None else text + "\n" + df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def plan_steps(df: DataFrame) -> dict[str, int]:
    """Shuffles, broadcasts, sorts and Python nodes of a physical plan before it runs: what a launch is on a cluster."""
    text = df._jdf.queryExecution().executedPlan().toString()
    count = lambda pattern: len(re.findall(pattern, text))
    return {"shuffles": count(r"(?m)\bExchange (?:hash|range|Single|Round)"), "broadcasts": count(r"BroadcastExchange"), "sorts": count(r"(?m)[-: ]Sort \["), "python": count(r"(?:FlatMap\w*|MapIn|Batch)\w*(?:Arrow|Pandas|Python)")}
