"""Measures of runs and of mined sets."""

from __future__ import annotations

import resource
import threading
import time
import uuid
from collections.abc import Callable
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.pattern import positive_part, positive_partner, text_of


def counts(patterns: DataFrame) -> DataFrame:
    """positives and negatives of a mined set."""
    return patterns.agg(F.coalesce(F.sum(F.when(F.col("n_neg") == 0, 1).otherwise(0)), F.lit(0)).cast("long").alias("positives"), F.coalesce(F.sum(F.when(F.col("n_neg") > 0, 1).otherwise(0)), F.lit(0)).cast("long").alias("negatives"))


def profile(items: DataFrame) -> DataFrame:
    """sequences, alphabet, mean_len, sd_len, max_len, mean_width of a view."""
    size = items.groupBy("sid", "pos").agg(F.count("*").alias("w"))
    per = size.groupBy("sid").agg(F.max("pos").alias("len"), F.sum("w").alias("w"), F.count("*").alias("sets"))
    a = per.agg(F.count("*").alias("sequences"), F.round(F.avg("len"), 6).alias("mean_len"), F.round(F.coalesce(F.stddev("len"), F.lit(0.0)), 6).alias("sd_len"), F.max("len").cast("long").alias("max_len"), F.round(F.sum("w") / F.sum("sets"), 6).alias("mean_width"))
    return a.crossJoin(items.agg(F.count_distinct("item").alias("alphabet")))


def overlap(left: DataFrame, right: DataFrame) -> DataFrame:
    """pattern, left_support, right_support (0 where a set lacks the pattern), side: full outer join of two mined sets."""
    a = left.select("pattern", F.col("support").alias("left_support"))
    b = right.select("pattern", F.col("support").alias("right_support"))
    side = F.when(F.col("right_support").isNull(), "left").when(F.col("left_support").isNull(), "right").otherwise("both")
    joined = a.join(b, "pattern", "full_outer").withColumn("side", side)
    return joined.select("pattern", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("left_support", "right_support")), "side")


def overlap_counts(left: DataFrame, right: DataFrame) -> DataFrame:
    return overlap(left, right).groupBy("side").agg(F.count("*").alias("patterns"))


def missed_by_partner(growth: DataFrame, partner: DataFrame, positives: DataFrame, low: int) -> DataFrame:
    """pattern, support, partner_support: found only by growth because the positive partner is rarer than low. positives: pattern, support of positive patterns counted without a limit."""
    only = growth.where("n_neg > 0").join(partner.select("pattern"), "pattern", "left_anti")
    keyed = only.select("pattern", "support", text_of(positive_partner("tokens")).alias("_key"))
    known = positives.select(F.col("pattern").alias("_key"), F.col("support").alias("partner_support"))
    return keyed.join(known, "_key", "left").select("pattern", "support", F.coalesce("partner_support", F.lit(0)).cast("long").alias("partner_support")).where(F.col("partner_support") < low)


def lost_by_gap(free: DataFrame, gapped: DataFrame) -> DataFrame:
    """Patterns that are frequent without the gap only."""
    return free.join(gapped.select("pattern"), "pattern", "left_anti")


def five_numbers(df: DataFrame, value: str, by: list[str]) -> DataFrame:
    """Exact minimum, quartiles and maximum for box plots."""
    q = F.percentile(F.col(value), F.array(*map(F.lit, (0.0, 0.25, 0.5, 0.75, 1.0))))
    return df.groupBy(*by).agg(q.alias("q")).select(*by, *(F.round(F.get("q", F.lit(i)), 6).alias(n) for i, n in enumerate(("least", "low", "middle", "high", "most"))))


def slope(df: DataFrame, y: str, x: str, by: list[str] | None = None) -> DataFrame:
    """Slope of log y over x, the rate of exponential growth."""
    return df.where(F.col(y) > 0).groupBy(*(by or [])).agg(F.round(F.regr_slope(F.log(F.col(y).cast("double")), F.col(x).cast("double")), 6).alias("slope"))


def recovery(truth: DataFrame, found: DataFrame) -> DataFrame:
    """planted, found_planted, recall, and precision among found patterns with an absence."""
    hit = truth.join(found.select("pattern").distinct(), "pattern", "left_semi").agg(F.count("*").alias("found_planted"))
    return truth.agg(F.count("*").alias("planted")).crossJoin(hit).crossJoin(found.where("n_neg > 0").agg(F.count("*").alias("mined"))).select("planted", "found_planted", F.round(F.col("found_planted") / F.nullif(F.col("planted"), F.lit(0)), 6).alias("recall"), F.round(F.col("found_planted") / F.nullif(F.col("mined"), F.lit(0)), 6).alias("precision"))


def sampled(items: DataFrame, one_of: int, seed: int = 0) -> DataFrame:
    """Sequences of one in so many, by a hash of their id."""
    mark = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("sid").cast("string"))), 1, 8), 16, 10).cast("long")
    return items.where(mark % one_of == 0)


def sample_bound(n: int, delta: float = 0.01) -> float:
    """Hoeffding: an estimate of a share from n sequences is off by at most this with probability 1 - delta."""
    import math

    return math.sqrt(math.log(2 / delta) / (2 * max(n, 1)))


def two_phase(items: DataFrame, sequences: DataFrame, sigma: float, options, one_of: int = 10, delta: float = 0.01) -> DataFrame:
    """Mine a sample at a threshold lowered by the bound, then count what it gives in one exact scan. pattern, estimate, support, rel_support."""
    from ..functions.semantics import GROWTH, Constraints
    from .growth import mine, n_sequences
    from .matching import support

    part = sampled(items, one_of)
    n = n_sequences(part)
    low = max(1, int((sigma - sample_bound(n, delta)) * n))
    rough = mine(part, low, options).select("pattern", F.round(F.col("support") / F.lit(max(n, 1)), 6).alias("estimate"))
    texts = [r[0] for r in rough.select("pattern").orderBy("pattern").collect()]
    exact = support(sequences, texts, GROWTH, Constraints(options.maxgap, options.maxspan))
    return exact.where(F.col("rel_support") >= sigma).join(rough, "pattern").select("pattern", "estimate", "support", "rel_support")


@contextmanager
def time_limit(spark: SparkSession, seconds: float):
    """Cancels the jobs of the block after so many seconds; yields a dict whose status becomes 'timeout'."""
    group, state = f"limit-{uuid.uuid4().hex}", {"status": "done"}
    spark.sparkContext.setJobGroup(group, "a run with a time limit", interruptOnCancel=True)

    def stop() -> None:
        state["status"] = "timeout"
        spark.sparkContext.cancelJobGroup(group)

    timer = threading.Timer(seconds, stop)
    timer.start()
    try:
        yield state
    except Exception:
        if state["status"] != "timeout":
            raise
    finally:
        timer.cancel()
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def timed(spark: SparkSession, run: Callable[[], DataFrame], seconds: float = 300) -> dict:
    """Wall seconds of a materialised run, its rows, status and the driver's peak memory in kb. A run that is stopped is flagged, not dropped."""
    began, rows = time.perf_counter(), None
    with time_limit(spark, seconds) as state:
        rows = run().count()
    return {"seconds": round(time.perf_counter() - began, 3), "rows": rows, "status": state["status"], "driver_kb": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss}


def item_masks(items: DataFrame, words: list[str]) -> DataFrame:
    """sid, mask: the items of a sequence as bits, of at most 63 words."""
    if len(words) > 63:
        raise ValueError("a mask has room for 63 items")
    bit = F.element_at(F.create_map(*(F.lit(x) for k, w in enumerate(words) for x in (w, 1 << k))), F.col("item"))
    return items.where(F.col("item").isin(words)).groupBy("sid").agg(F.bit_or(bit).alias("mask"))


def middle(values: pd.Series) -> float:
    """The median, as a grouped Arrow aggregate."""
    return float(values.median())


def frontier_sizes(rows: DataFrame, by: list[str]) -> DataFrame:
    """Sequences and the median number of rows that a sequence has, of each group: rows by, sid."""
    per = rows.groupBy(*by, "sid").agg(F.count("*").cast("double").alias("n"))
    return per.groupBy(*by).agg(F.pandas_udf(middle, "double")("n").alias("middle"))


def partner_state(positives: DataFrame) -> DataFrame:
    """Rows of sequence ids that the partner miner holds: the sum of the supports of all its positives."""
    return positives.agg(F.sum("support").alias("state_rows"))


__all__ = ["counts", "five_numbers", "lost_by_gap", "missed_by_partner", "overlap", "overlap_counts", "partner_state", "positive_part", "profile", "recovery", "sample_bound", "sampled", "slope", "time_limit", "timed", "two_phase"]
