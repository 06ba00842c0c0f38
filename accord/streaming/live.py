"""Event-time windows, and live detection with state per video.

Every function of a stream takes and returns DataFrames and works on batches as well: a batch twin is the same plan without a watermark.
Patterns are sums over pairs, so the order in which pairs come doesn't matter.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from accord.operators import grouping


def timed(events: DataFrame, delay: str | None = None) -> DataFrame:
    """ts as a timestamp, which watermarks ask for; delay sets the watermark."""
    out = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return out.withWatermark("ts", delay) if delay else out


def tumbling(events: DataFrame, width: str = "3 days") -> DataFrame:
    """Windows of the width, starting on 2024-01-01 and every width before and after."""
    w = F.window("ts", width, startTime="1 day")
    return events.groupBy("user_id", w, "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean"))


def frame_of(start: Column) -> Column:
    return F.floor(F.datediff(start.cast("date"), F.lit("2024-01-01").cast("date")) / 3).cast("int")


def sliding(events: DataFrame, width: str = "3 days", step: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))


def once(events: DataFrame, *keys: str) -> DataFrame:
    """The first of equal rows within the watermark."""
    return events.dropDuplicatesWithinWatermark(list(keys))


def with_template(patterns: DataFrame, template: DataFrame) -> DataFrame:
    """A stream of packed patterns against a static template of one row."""
    return patterns.crossJoin(F.broadcast(template.select(F.col("tri").alias("template_tri")).limit(1)))


def matched(frames: DataFrame, landmarks: DataFrame, slack: str = "10 seconds") -> DataFrame:
    """Two streams joined by video and frame, their times at most slack apart; state of either side goes when the watermarks pass."""
    f, m = frames.alias("f"), landmarks.alias("m")
    near = F.expr(f"m.ts BETWEEN f.ts - INTERVAL {slack} AND f.ts + INTERVAL {slack}")
    return f.join(m, (F.col("f.video_id") == F.col("m.video_id")) & (F.col("f.t") == F.col("m.t")) & near).select("f.video_id", "f.t", "f.ts", "m.motion")


#: Frames behind a video's last one that are still known as seen after their numbers have been let go.
KEPT = 64
_STATE = "tri binary, diag double, n_pairs bigint"
_OUT = "video_id string, n_pairs bigint, distance double, decision int, final boolean"


def js(p: np.ndarray, q: np.ndarray) -> float:
    half = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        a, b = np.where(p > 0, p * np.log(p / half), 0), np.where(q > 0, q * np.log(q / half), 0)
    return float((a + b).sum() / 2)


def detector(template: np.ndarray, threshold: float, marks: tuple = (1, 10, 35, 70), n: int = 51, idle_ms: int = 60_000, event_time: bool = False):
    """The stateful function of detect(): the state is a video's running pattern, of a fixed size whatever the video's length. Pairs of a batch are summed together
    from one mark to the next."""
    i, j = low = np.tril_indices(n, -1)

    def run(key, batches: Iterator, state) -> Iterator:
        import pandas as pd

        tri, diag, count = (np.frombuffer(state.get[0]).copy(), state.get[1], state.get[2]) if state.exists else (np.zeros(len(low[0])), 0.0, 0)

        def row(final: bool):
            total = 2 * tri.sum() + n * diag
            d = js(tri / total, template) if total else 0.0
            return pd.DataFrame([(key[0], count, d, int(d >= threshold), final)], columns=["video_id", "n_pairs", "distance", "decision", "final"])

        if state.hasTimedOut:
            yield row(True)
            state.remove()
            return
        for b in batches:
            if not len(b):
                continue
            lab, w = np.stack(b["labels"].to_numpy()), b["w"].to_numpy(float)
            ends = sorted({m - count for m in marks if 0 < m - count <= len(b)} | {len(b)})
            for s, e in zip([0, *ends], ends):
                tri += w[s:e] @ (lab[s:e][:, i] == lab[s:e][:, j])
                diag += w[s:e].sum()
                count += e - s
                if count in marks:
                    yield row(False)
        state.update((tri.tobytes(), float(diag), count))
        if event_time:
            state.setTimeoutTimestamp(state.getCurrentWatermarkMs() + idle_ms)
        else:
            state.setTimeoutDuration(idle_ms)

    return run


def detect(groups: DataFrame, template: np.ndarray, threshold: float, event_time: bool = False, **options) -> DataFrame:
    """(video_id, n_pairs, distance, decision, final) of a stream of grouped pairs (video_id, labels, w): a row when a video's pairs reach each mark, and a last one when
    it falls idle. event_time: idle by the watermark, which the stream must have, and not by the clock."""
    f = detector(template, threshold, event_time=event_time, **options)
    return groups.groupBy("video_id").applyInPandasWithState(f, _OUT, _STATE, "append", "EventTimeTimeout" if event_time else "ProcessingTimeTimeout")


def pairer(stride: int = 1, idle_ms: int = 60_000):
    """The stateful function of paired(): the state has the frames that still wait for a neighbour, and goes when the watermark is idle_ms past a video's last frame."""

    def run(key, batches: Iterator, state) -> Iterator:
        import pandas as pd

        if state.hasTimedOut:
            state.remove()
            return
        held = dict(zip(state.get[0], state.get[1])) if state.exists else {}
        out, gone = [], set()
        for b in batches:
            for t, at in zip(b["t"].tolist(), b["position"]):
                if t in held:
                    continue  # a frame that comes twice counts once
                held[t] = np.asarray(at, float).ravel().tobytes()
                for first in (t - stride, t):
                    if held.get(first) and held.get(first + stride):
                        move = (np.frombuffer(held[first + stride]) - np.frombuffer(held[first])).reshape(-1, 2)
                        out.append((key[0], first, [{"dx": x, "dy": y} for x, y in move.tolist()]))
        for t in [t for t in held if t - stride in held and t + stride in held]:
            gone.add(t)  # both its pairs are out: its numbers can go
        for t in gone:
            held[t] = b""
        last = max(held, default=0)
        held = {t: v for t, v in held.items() if v or t > last - KEPT * stride}
        state.update((list(held), list(held.values())))
        state.setTimeoutTimestamp(state.getCurrentWatermarkMs() + idle_ms)
        if out:
            yield pd.DataFrame(out, columns=["video_id", "t", "motion"])

    return run


def paired(frames: DataFrame, stride: int = 1, idle_ms: int = 60_000) -> DataFrame:
    """(video_id, t, motion) of a stream of frames (video_id, t, ts, position array<double>: x and y of each landmark in turn), in whatever order they come: a pair as soon as
    both its frames are there. The stream must have a watermark on ts; frames behind it are dropped."""
    f = pairer(stride, idle_ms)
    schema, state = "video_id string, t int, motion array<struct<dx:double,dy:double>>", "ts array<int>, positions array<binary>"
    return frames.groupBy("video_id").applyInPandasWithState(f, schema, state, "append", "EventTimeTimeout")


def grouped(pairs: DataFrame, o: grouping.Options = grouping.Options()) -> DataFrame:
    """The same kernel as in batches: it needs no state."""
    return grouping.group_pairs(pairs, o).withColumn("w", F.col("k") * F.col("score"))
