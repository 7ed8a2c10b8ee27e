"""A monitor of patterns on an event stream, under total absence and soft occurrence.

Rows wait in state until the watermark passes them, then count in the order of their time, so arrival
order does not matter; rows behind the watermark are dropped and show in the query's metric of
late rows. Per pattern and slot the state holds its live ends: the latest position, or with maxspan
the pairs (position, start) that no other beats. An itemset with a negated item ends what waits before it.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.pattern import Pattern, parse
from ..functions.semantics import FREE, Constraints

OUTPUT = "sid long, pattern string, at timestamp, position long"


class Tracker:
    """State of one sequence. live[p][k]: ends of pattern p after its positive itemset k."""

    def __init__(self, patterns: list[Pattern], c: Constraints, saved: dict | None = None):
        self.patterns, self.c = patterns, c
        self.position = saved["position"] if saved else 0
        self.live = saved["live"] if saved else [[[] for _ in p.positives] for p in patterns]

    def saved(self) -> dict:
        return {"position": self.position, "live": self.live}

    def _add(self, ends: list[list[int]], pos: int, start: int) -> list[list[int]]:
        if self.c.maxspan is None:
            return [[pos, start]] if not ends or ends[0][0] <= pos else ends
        kept = [e for e in ends if not (e[0] <= pos and e[1] <= start)]
        return [*kept, [pos, start]] if not any(e[0] >= pos and e[1] >= start for e in kept) else kept

    def step(self, itemset: set[str]) -> list[str]:
        """Take the next itemset; returns the patterns that complete at it."""
        self.position += 1
        t, done = self.position, []
        for p, live in zip(self.patterns, self.live, strict=True):
            for k in range(len(p.positives) - 1, -1, -1):
                if set(p.positives[k]) <= itemset:
                    if k == 0:
                        starts = [t]
                    else:
                        starts = [s for e, s in live[k - 1] if e < t and (self.c.maxgap is None or t - e <= self.c.maxgap) and (self.c.maxspan is None or t - s <= self.c.maxspan)]
                    for s in starts:
                        live[k] = self._add(live[k], t, s)
                    if starts and k == len(p.positives) - 1:
                        done.append(p.text)
            for k, q in enumerate(p.absences):
                if itemset & set(q):
                    live[k] = [e for e in live[k] if e[0] == t]
        return done


def monitor(events: DataFrame, patterns: list[str], c: Constraints = FREE, delay: str = "1 hour", idle_seconds: int | None = None) -> DataFrame:
    """events: sid long, at timestamp, item string (streaming). Rows of equal time form an itemset. Emits each completion. A sequence without a row for idle_seconds of event time is forgotten, with its position; None keeps all."""
    parsed = [parse(p) for p in patterns]

    def run(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        saved = json.loads(state.get[0]) if state.exists else {"tracker": None, "waiting": []}
        tracker, waiting = Tracker(parsed, c, saved["tracker"]), saved["waiting"]
        if not state.hasTimedOut:
            for pdf in parts:
                waiting += [[int(t.value // 1000), x] for t, x in zip(pdf["at"], pdf["item"], strict=True)]
        mark = state.getCurrentWatermarkMs() * 1000
        ready = sorted(w for w in waiting if w[0] <= mark)
        waiting = [w for w in waiting if w[0] > mark]
        rows, i = [], 0
        while i < len(ready):
            j = i
            while j < len(ready) and ready[j][0] == ready[i][0]:
                j += 1
            rows += [(key[0], p, pd.Timestamp(ready[i][0], unit="us"), tracker.position) for p in tracker.step({x for _, x in ready[i:j]})]
            i = j
        last = max([saved.get("last", 0), *(w[0] for w in ready)])
        idle = None if idle_seconds is None else last + idle_seconds * 1_000_000
        if not waiting and idle is not None and idle <= mark:
            if state.exists:
                state.remove()
            yield pd.DataFrame(rows, columns=["sid", "pattern", "at", "position"])
            return
        state.update((json.dumps({"tracker": tracker.saved(), "waiting": waiting, "last": last}),))
        if not waiting and idle is not None:
            state.setTimeoutTimestamp(max(idle // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        if waiting:
            state.setTimeoutTimestamp(max(min(w[0] for w in waiting) // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(rows, columns=["sid", "pattern", "at", "position"])

    clean = events.where("sid is not null and at is not null and item is not null").withWatermark("at", delay)
    return clean.groupBy("sid").applyInPandasWithState(run, OUTPUT, "saved string", "append", GroupStateTimeout.EventTimeTimeout)


def replay(events: DataFrame, patterns: list[str], c: Constraints = FREE, delay: str = "1 hour", slices: int = 4, path: str = "") -> DataFrame:
    """All completions of a finite table (sid, at, item), sent through monitor() in order of time; path: a shared folder.

    Each slice of time is written and run to its end before the next, so no row is late whatever order a source reads files in. A closing row beyond the last event then
    moves the watermark past all that waits; it is later than any other row and so completes nothing."""
    spark = events.sparkSession
    clean = events.select(F.col("sid").cast("long").alias("sid"), F.col("at").cast("timestamp").alias("at"), F.col("item").cast("string").alias("item")).where("sid is not null and at is not null and item is not null")
    if clean.isEmpty():
        return spark.createDataFrame([], OUTPUT)
    second = F.unix_timestamp("at")
    cuts = sorted(set(clean.select(second.cast("double").alias("x")).approxQuantile("x", [k / slices for k in range(1, slices)], 0.01)))
    parts = [clean.where((second > low if low is not None else F.lit(True)) & (second <= high if high is not None else F.lit(True))) for low, high in zip([None, *cuts], [*cuts, None], strict=True)]
    closing = clean.agg(F.max("sid").alias("sid"), (F.max("at") + F.expr(f"interval {delay}") + F.expr("interval 1 second")).alias("at")).select("sid", "at", F.lit("").alias("item"))
    for part in [*parts, closing]:
        part.write.mode("append").parquet(f"{path}/in")
        found = monitor(spark.readStream.schema(clean.schema).parquet(f"{path}/in"), patterns, c, delay)
        found.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(OUTPUT).parquet(f"{path}/out")


def item_rates(events: DataFrame, window: str, slide: str | None = None, session: str | None = None, delay: str = "1 hour") -> DataFrame:
    """Events per item and tumbling, sliding or session window."""
    span = F.session_window("at", session) if session else F.window("at", window, slide)
    return events.withWatermark("at", delay).groupBy(span.alias("w"), "item").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "item", "n")


def remine(stream: DataFrame, store_path: str, patterns_path: str, mine_items, checkpoint: str):
    """Append each micro-batch of (sid, pos, item) to the store and mine it anew; mine_items: items -> patterns. Batches are written under their number, so one that is run twice counts once."""

    def batch(df: DataFrame, number: int) -> None:
        df.write.mode("overwrite").parquet(f"{store_path}/batch={number}")
        items = df.sparkSession.read.parquet(store_path).select("sid", "pos", "item").distinct()
        mine_items(items).write.mode("overwrite").parquet(f"{patterns_path}/batch={number}")

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint)
