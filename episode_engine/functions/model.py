"""Serial episodes: ordered event types with a lower (open) and an upper (closed) bound on each gap."""

from __future__ import annotations

import re
from dataclasses import dataclass
from datetime import timedelta

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

NODES = "episode_id string, pos int, event_type string, low long, high long, n int"


def _micros(x: int | timedelta | None) -> int | None:
    return int(x / timedelta(microseconds=1)) if isinstance(x, timedelta) else x


@dataclass(frozen=True)
class Episode:
    """types[i+1] follows types[i] by more than low[i] and at most high[i]; a high of None has no bound."""

    episode_id: str
    types: tuple[str, ...]
    low: tuple[int, ...]
    high: tuple[int | None, ...]

    def __post_init__(self) -> None:
        if not self.types or len(self.low) != len(self.types) - 1 or len(self.high) != len(self.low):
            raise ValueError("an episode has a type and, for each further one, a gap")
        if any(a < 0 or (b is not None and b <= a) for a, b in zip(self.low, self.high, strict=True)):
            raise ValueError("gaps are 0 <= low < high")

    @classmethod
    def of(cls, *types: str, gaps: list | None = None, episode_id: str | None = None) -> Episode:
        gaps = [(0, None)] * (len(types) - 1) if gaps is None else gaps
        low, high = tuple(_micros(a) for a, _ in gaps), tuple(_micros(b) for _, b in gaps)
        return cls(episode_id or ">".join(types), tuple(types), low, high)

    @classmethod
    def parse(cls, text: str, episode_id: str | None = None) -> Episode:
        """`view -(5,10]-> click -> purchase`, in integer ticks."""
        parts = re.split(r"\s*-(?:\((\d+),(\d+|inf)\]-)?>\s*", text.strip())
        gaps = [(int(a or 0), None if b in (None, "inf") else int(b)) for a, b in zip(parts[1::3], parts[2::3], strict=True)]
        return cls.of(*parts[::3], gaps=gaps, episode_id=episode_id or text.strip())

    def __len__(self) -> int:
        return len(self.types)

    @property
    def span(self) -> int | None:
        """The longest time from start to end, None without bound."""
        return None if any(h is None for h in self.high) else sum(self.high)

    def reversed(self) -> Episode:
        return Episode(self.episode_id, self.types[::-1], self.low[::-1], self.high[::-1])


def span(episodes: list[Episode]) -> int | None:
    spans = [e.span for e in episodes]
    return None if None in spans else max(spans, default=0)


def episode_nodes(spark: SparkSession, episodes: list[Episode]) -> DataFrame:
    """A row for each node; low and high are those of the gap before it (null for the first)."""
    rows = [(e.episode_id, i, ty, e.low[i - 1] if i else None, e.high[i - 1] if i else None, len(e)) for e in episodes for i, ty in enumerate(e.types)]
    return spark.createDataFrame(rows, NODES)


def gap_ok(gap: Column, low, high) -> Column:
    """Open below, closed above; a null or None high has no bound."""
    low = low if isinstance(low, Column) else F.lit(low)
    if high is None:
        return gap > low
    high = high if isinstance(high, Column) else F.lit(high)
    return (gap > low) & (high.isNull() | (gap <= high))


def expand_roles(ev: DataFrame, episodes: list[Episode]) -> DataFrame:
    """Which event can play which node: the few nodes are broadcast (k * N rows)."""
    return ev.join(F.broadcast(episode_nodes(ev.sparkSession, episodes)), "event_type")
