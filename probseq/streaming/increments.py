"""Structured Streaming around the incremental miner: increments, sequences from events, late rows, growing sequences."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from probseq.operators.incremental import Maintainer


def run_increments(stream: DataFrame, maintainer: Maintainer, checkpoint: str, trigger: dict | None = None) -> StreamingQuery:
    """Feeds micro-batches of occurrences (seq_id, pos, item, p) to a maintainer.

    Whole sequences arrive in one batch. The batch id is the version of the state: a replayed batch reads the version
    before it and overwrites its own, so it changes nothing.
    """

    def take(batch: DataFrame, batch_id: int) -> None:
        own = batch.persist()
        try:
            if batch_id == 0:
                maintainer.initialize(own, 0)
            else:
                maintainer.apply(own, batch_id)
        finally:
            own.unpersist()

    return stream.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def timed_events(stream: DataFrame, ts: str = "ts", delay: str = "1 day") -> DataFrame:
    """Event time as a timestamp with a watermark; the tables' own type has none."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """A closed session of a user is a new sequence: (user_id, start, events); append mode."""
    own = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_type"))).alias("events"))
    return own.select("user_id", F.col("w.start").alias("start"), "events")


def days(events: DataFrame) -> DataFrame:
    """A user's day is a sequence."""
    own = events.groupBy("user_id", F.window("ts", "1 day").alias("w")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_type"))).alias("events"))
    return own.select("user_id", F.col("w.start").alias("start"), "events")


def sliding(events: DataFrame, size: str = "1 day", step: str = "6 hours") -> DataFrame:
    """Overlapping windows: for looking, as overlapping sequences must not be added up."""
    own = events.groupBy("user_id", F.window("ts", size, step).alias("w")).agg(F.count(F.lit(1)).alias("events"))
    return own.select("user_id", F.col("w.start").alias("start"), "events")


def without_repeats(events: DataFrame, key: str = "event_id") -> DataFrame:
    """Drops repeats of a key that come within the watermark."""
    return events.dropDuplicatesWithinWatermark([key])


def as_occurrences(sequences: DataFrame, probability=None) -> DataFrame:
    """(seq_id, pos, item, p) of rows with `events`; ids are hashes of user and start."""
    at = sequences.select(F.xxhash64("user_id", "start").alias("seq_id"), F.posexplode("events").alias("k", "e"))
    return at.select("seq_id", (F.col("k") + 1).alias("pos"), F.col("e.event_type").alias("item"), (F.lit(1.0) if probability is None else probability).alias("p"))


def with_weights(occ: DataFrame, weights: DataFrame) -> DataFrame:
    """Stream-static join: every micro-batch sees the current weights."""
    return occ.join(weights, "item", "left")


def growing_support(occ: DataFrame, patterns: list[list[list[str]]]) -> DataFrame:
    """(pattern_no, seq_id, change): how the best match of each pattern in a growing sequence changes.

    A sequence that grows takes back its old contribution: the sum of changes is always the expected support. State
    per sequence: its events so far and its contributions.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        pos, item, p, old = state.get if state.exists else ([], [], [], [0.0] * len(patterns))
        pos, item, p = list(pos), list(item), list(p)
        for b in batches:
            pos += b["pos"].tolist()
            item += b["item"].tolist()
            p += b["p"].tolist()
        by: dict[int, dict[str, float]] = {}
        for a, i, x in zip(pos, item, p, strict=True):
            by.setdefault(a, {})[i] = max(x, by.get(a, {}).get(i, 0.0))
        events = [by[a] for a in sorted(by)]
        new = [best_match(events, want) for want in patterns]
        state.update((pos, item, p, new))
        change = np.array(new) - np.array(list(old))
        hit = np.flatnonzero(change)
        yield pd.DataFrame({"pattern_no": hit, "seq_id": key[0], "change": change[hit]})

    return occ.groupBy("seq_id").applyInPandasWithState(
        step, "pattern_no long, seq_id long, change double", "pos array<long>, item array<string>, p array<double>, old array<double>", "append", GroupStateTimeout.NoTimeout
    )


def best_match(events: list[dict[str, float]], want: list[list[str]]) -> float:
    """The best match probability of a pattern in one sequence, in one sweep per event of the pattern."""
    ends: list[float] | None = None
    for items in want:
        best, new = (1.0 if ends is None else 0.0), []
        for k, event in enumerate(events):
            here = 1.0
            for i in items:
                here *= event.get(i, 0.0)
            new.append(here * best)
            if ends is not None:
                best = max(best, ends[k])
        ends = new
    return max(ends or [0.0], default=0.0)


def dropped_rows(query: StreamingQuery) -> int:
    """Rows that came behind the watermark so far."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p.get("stateOperators", []))


def late_and_timely(events: DataFrame, horizon) -> tuple[DataFrame, DataFrame]:
    """(late, timely) rows of a batch against a time: late ones can be mined as an increment of their own."""
    return events.where(F.col("ts") < horizon), events.where(F.col("ts") >= horizon)
