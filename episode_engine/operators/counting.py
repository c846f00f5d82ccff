"""The decomposition: a superset of occurrences by tracking, then overlap removal."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..functions.model import Episode, span
from ..plans.planner import default_segment
from . import scheduling, segments, tracking
from .serial import _all_counts

TRACKING = {
    "asof": tracking.track_window_asof,
    "range": tracking.track_window_range,
    "union": tracking.track_union_asof,
    "pruned": tracking.track_forward_pruned,
    "all": tracking.track_forward_all,
    "backward": tracking.track_backward,
    "kernel": tracking.track_kernel,
}


def count_nonoverlapping(ev: DataFrame, episodes: list[Episode], tracking: str = "auto", schedule: str = "auto", seg_len: int | None = None) -> DataFrame:
    """episode_id, stream_key, n: the largest number of occurrences without overlap, zeros included.

    Streams are cut into segments of seg_len ticks with a halo; without it the length follows from the number of events (planner).
    By default tracking and the tables of overlap removal are made in one pass over each segment; a named way of
    tracking runs as a plan of its own before them. Episodes with an unbounded gap are tracked and scheduled whole.
    """
    reach = span(episodes)
    if schedule in ("auto", "segments") and reach is not None:
        seg_len = seg_len or default_segment(ev, reach)
        counts = segments.count_segments(ev, episodes, seg_len) if tracking == "auto" else scheduling.schedule_segments(TRACKING[tracking](ev, episodes, seg_len), seg_len)
        return _all_counts(counts, ev, episodes)
    gaps = {(e.low, e.high) for e in episodes}
    how = tracking if tracking != "auto" else ("asof" if len(gaps) <= 3 else "union")
    occ = TRACKING[how](ev, episodes, seg_len)
    schedule = "islands" if schedule in ("auto", "segments") else schedule
    counts = {"fold": scheduling.schedule_fold, "kernel": scheduling.schedule_kernel, "islands": scheduling.schedule_islands, "jump": scheduling.schedule_jump}[schedule](occ)
    return _all_counts(counts, ev, episodes)
